"""Line deduplication with DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, rows_of, written

_STRIPPED = " \t\n\x0b\x0c\r"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def line_key(line: Column) -> Column:
    """The line without ASCII white space at its ends and with A-Z lower-cased. Pure ASCII takes the fast lower()."""
    bare = F.btrim(line, F.lit(_STRIPPED))
    return F.when(F.length(bare) == F.octet_length(bare), F.lower(bare)).otherwise(F.translate(bare, _UPPER, _LOWER))


def dedup_lines(docs: DataFrame, threshold: int = 10, min_chars: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Drop each line whose key is found in `threshold` documents or more, in every document.

    Returns the columns of `docs` with the text replaced, plus n_lines (before) and n_dropped; input columns of these
    two names are replaced. A null or empty text is one empty line. Keys shorter than `min_chars` code points are
    never dropped. Rows that repeat an id (or a null id) count as one document for the threshold, but each row is
    returned and loses only its own frequent lines: rows are told apart by id and a hash of the text. All lines
    dropped: the text is empty.

    Plan: (key hashes, id, text hash, position) rows are all that is exploded and shuffled. Keys are counted over distinct
    (key, id) pairs, first by both columns, so that one very common line is spread over all tasks, then by key with
    partial sums. The frequent keys are written before the lines are joined with them: their measured size decides whether
    they are broadcast, and otherwise both sides of the join are plain, so that AQE splits the lines of a hot key. Texts
    are shuffled once, by id and text hash, so that rows with a null id are spread, too.
    """
    names = docs.columns
    lines_col, drop_col, keep_col, hash_col = (free_name(names, n) for n in ("lines", "dropped_at", "kept_at", "text_hash"))
    split = F.split(F.coalesce(F.col(f"`{text_col}`"), F.lit("")), "\n", -1)
    hashed = F.xxhash64(F.coalesce(F.col(f"`{text_col}`"), F.lit("")))
    lines = rows_of(docs, id=id_col, text_hash=hashed, lines=split).select("id", "text_hash", F.posexplode("lines").alias("pos", "line"))
    keyed = lines.select("id", "text_hash", "pos", line_key(F.col("line")).alias("key")).where(F.length("key") >= min_chars)
    keyed = keyed.select("id", "text_hash", "pos", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(1), "key").alias("h2"))
    common = keyed.select("h1", "h2", "id").distinct().groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= threshold).select("h1", "h2")
    common = written(common, "frequent-lines")
    dropped = keyed.join(common, ["h1", "h2"]).groupBy("id", "text_hash").agg(F.collect_set("pos").alias("at"))
    found = dropped.select(F.col("id").alias(free_name(names, "dropped_id")), F.col("text_hash").alias(free_name([*names, hash_col], "dropped_hash")), F.col("at").alias(drop_col))
    held = docs.withColumn(lines_col, split).withColumn(hash_col, hashed).drop(text_col)
    joined = held.join(found, F.col(f"`{id_col}`").eqNullSafe(F.col(found.columns[0])) & (F.col(hash_col) == F.col(found.columns[1])), "left")
    n = F.size(lines_col)
    at = F.coalesce(F.col(drop_col), F.array().cast("array<int>"))
    out = joined.withColumn(keep_col, F.array_except(F.sequence(F.lit(0), n - 1), at))
    text = F.array_join(F.transform(keep_col, lambda i: F.get(F.col(lines_col), i)), "\n")
    counted = {"n_lines": n.cast("long"), "n_dropped": (n - F.size(keep_col)).cast("long")}
    made = {text_col: text} | counted
    kept = [c for c in names if c.lower() not in counted]
    return out.select(*[made[c].alias(c) if c in made else F.col(f"`{c}`") for c in kept], *[v.alias(k) for k, v in counted.items()])


def op2_line_dedup(spark, sf_dir: str) -> DataFrame:
    out = dedup_lines(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text"), 256).alias("kept_sha256"))


OP2_SQL = r"""
with lines as (
  select doc_id, unnest(string_split(coalesce(text, ''), chr(10))) as line, unnest(range(1, len(string_split(coalesce(text, ''), chr(10))) + 1)) as pos
  from documents
), keyed as (
  select doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key
  from lines
), frequent as (
  select key from keyed where length(key) >= 1 group by key having count(distinct doc_id) >= 10
), flagged as (
  select k.doc_id, k.pos, k.line, f.key is not null as gone from keyed k left join frequent f on k.key = f.key
)
select doc_id, count(*)::bigint as n_lines, count(*) filter (where gone)::bigint as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by pos) filter (where not gone), '')) as kept_sha256
from flagged group by doc_id
"""
