"""A training corpus from raw documents, in five stages; each is written as Parquet and read again by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sizeprofile.llm.bpe import bpe_encode
from sizeprofile.llm.common import written
from sizeprofile.llm.jaccard_join import jaccard_components
from sizeprofile.llm.line_dedup import dedup_lines
from sizeprofile.llm.mixing import label_domains, mix_to_targets
from sizeprofile.llm.quality_rules import quality_rules

#: Near duplicates: five-word shingles, similarity 0.8.
SHINGLE_WORDS, SIMILARITY_PERCENT = 5, 80
#: Shares of the token total by label domain, the total as a multiple of the present one, and the bounds of the rates.
#: No rate is below 1: mixing repeats documents, and drops none that the filters have kept. Memberships of filtered text
#: are soft, so thinning would drop good documents for little: README.md has the figures.
MIX = {"good": 0.88, "good_toxic": 0.08, "poor": 0.03, "poor_toxic": 0.01}
MIX_TOTAL, MIX_LEAST, MIX_MOST = 1.1, 1.0, 3.0


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the distribution divergence reject go. An empty table stays empty."""
    return quality_rules(docs).where("kept").select(*_columns(docs))


def lines_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines found in ten documents or more go from all texts; n_chars is that of the text that is left."""
    out = dedup_lines(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*_columns(docs))


def near_duplicates_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents, the one with the smallest id stays. Rows that repeat an id stay or go together; documents without words stay."""
    groups = jaccard_components(docs.select("doc_id", "text"), SIMILARITY_PERCENT, SHINGLE_WORDS)
    stays = groups.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("kept_id")).distinct()
    return docs.join(stays, F.col("doc_id").eqNullSafe(F.col("kept_id")), "left_semi").select(*_columns(docs))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are repeated by the rates that bring the domains of the labels table to their target weights."""
    labels = label_domains(spark.read.parquet(f"{sf_dir}/labels.parquet"))
    mixed = mix_to_targets(docs, labels, MIX, MIX_TOTAL, MIX_LEAST, MIX_MOST)
    return mixed.withColumn("copies", F.explode(F.expr("sequence(1, copies)"))).select(*_columns(docs))


def tokens_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, n_tokens and the ids (little-endian unsigned 32-bit) of every row."""
    import public_tokenizers

    encoded = bpe_encode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
    return encoded.select("doc_id", "lang", "source", F.expr("octet_length(ids) div 4").cast("long").alias("n_tokens"), "ids")


def _columns(docs: DataFrame) -> list:
    return [F.col(f"`{c}`") for c in docs.columns]


STAGES = [("quality_rules", quality_stage), ("line_dedup", lines_stage), ("near_duplicates", near_duplicates_stage), ("mixing", mixing_stage), ("bpe", tokens_stage)]

#: The classifier, the gradient steps and the tokenizer are not expressible in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = written(docs, name)
    return docs
