"""Quality rules by distribution divergence from language references."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CONTINUATION, SPACE, batches_of, free_name, mapped, release_held, rows_of, texts_of, written

#: A word is a bin of its language's reference if it makes up this share of the language's words or more: 1/share bins at most.
COMMON_SHARE = 0.002
#: References sent along to all tasks: those of the languages with most words. Others are joined by language.
SENT_LANGUAGES = 1_000
#: Minimum-length guards: shorter documents get no verdict from the divergence, thinner references give none.
MIN_WORDS, MIN_REFERENCE_WORDS = 50, 2_000
#: Jensen-Shannon distances (square root of the base-2 divergence) above which a document is rejected.
MAX_CLASS_DISTANCE, MAX_WORD_DISTANCE = 0.3, 0.5

_SYMBOLS = b"#*$%&|<>"


def _byte_classes() -> np.ndarray:
    """256 x 7 indicator: lower, upper, digit, white space, common punctuation, other ASCII, first byte of a non-ASCII code point."""
    kind = np.full(256, 5)
    for k, group in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", SPACE, b".,;:!?'\"()-")):
        kind[list(group)] = k
    kind[0xC0:] = 6
    out = np.zeros((256, 7), dtype=np.int64)
    out[np.arange(256), kind] = 1
    out[0x80:0xC0] = 0  # continuation bytes
    return out


CLASSES = _byte_classes()


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a window of three words which is found twice or more."""
    n = len(words)
    if n < 4:
        return 0
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), dtype=np.int64, count=n)
    pairs = np.unique(ids[:-1] * len(number) + ids[1:], return_inverse=True)[1]
    _, which, count = np.unique(pairs[:-1] * np.int64(len(number)) + ids[2:], return_inverse=True, return_counts=True)
    hit = np.zeros(n, dtype=bool)
    starts = np.flatnonzero(count[which] > 1)
    for k in range(3):
        hit[starts + k] = True
    return int(hit.sum())


def base_counts(raw: bytes, words: list[bytes]) -> tuple[int, int, int, int]:
    """word_chars, n_symbols, n_dup_lines, n_repeat_words of a text."""
    chars = len(raw.translate(None, SPACE + CONTINUATION))
    symbols = len(raw) - len(raw.translate(None, _SYMBOLS))
    repeated = 0
    if b"\n" in raw:
        lines = [x for x in raw.split(b"\n") if x and not x.isspace()]
        repeated = len(lines) - len(set(lines))
    if len(set(zip(words, words[1:], words[2:]))) < len(words) - 2:
        return chars, symbols, repeated, repeated_words(words)
    return chars, symbols, repeated, 0


def class_counts(raw: bytes) -> np.ndarray:
    return np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256) @ CLASSES


def distance(p: np.ndarray, q: np.ndarray) -> float:
    """Jensen-Shannon distance of two histograms, 0 to 1. Empty histograms have no distance (0)."""
    if not p.sum() or not q.sum():
        return 0.0
    p, q = p / p.sum(), q / q.sum()
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        terms = np.where(p > 0, p * np.log2(p / m), 0) + np.where(q > 0, q * np.log2(q / m), 0)
    return float(np.sqrt(max(0.0, terms.sum() / 2)))


class Reference:
    """Histograms of one language: character classes, and common words with one bin for all others."""

    def __init__(self, classes: list[int], words: dict[bytes, int], n_words: int):
        self.classes = np.array(classes, dtype=float)
        self.words = sorted(words)
        self.n_words = n_words
        self.hist = np.array([*(words[w] for w in self.words), n_words - sum(words.values())], dtype=float)

    def distances(self, raw: bytes, words: list[bytes]) -> tuple[float, float]:
        seen = Counter(words)
        found = [seen.get(w, 0) for w in self.words]
        return distance(class_counts(raw), self.classes), distance(np.array([*found, len(words) - sum(found)], dtype=float), self.hist)


_COUNTS = pa.schema([("lang", pa.string()), ("bin", pa.int32()), ("word", pa.binary()), ("n", pa.int64())])
_WORD_BIN, _TOTAL_BIN = 100, 99
#: Distinct words that a task counts before it hands on partial counts.
_HELD_WORDS = 200_000


def _partial_counts(batches):
    """Partial counts of a task's rows: by language, of each character class, of all words and of each word."""
    release_held()
    words: dict[str | None, Counter] = {}
    sums: dict[str | None, np.ndarray] = {}

    def flush():
        for lang, seen in words.items():
            yield from ((lang, _WORD_BIN, w, n) for w, n in seen.items())
            yield (lang, _TOTAL_BIN, b"", seen.total())
            yield from ((lang, k, b"", int(n)) for k, n in enumerate(sums[lang]))
        words.clear()
        sums.clear()

    for batch in batches:
        for lang, raw in zip(batch.column(0).to_pylist(), texts_of(batch, "text")):
            words.setdefault(lang, Counter()).update(raw.split())
            sums[lang] = sums.get(lang, 0) + class_counts(raw)
        if sum(map(len, words.values())) > _HELD_WORDS:
            yield from batches_of(_COUNTS, flush(), 50_000)
    yield from batches_of(_COUNTS, flush(), 50_000)


def language_references(docs: DataFrame, lang_col: str = "lang", text_col: str = "text") -> tuple[dict[str, Reference], DataFrame | None]:
    """References of all languages of MIN_REFERENCE_WORDS words or more, from all texts of the table; null has none.

    Those of the SENT_LANGUAGES languages with most words come to the driver, with 1/COMMON_SHARE words each at most;
    so that is bounded by the two parameters, not by the data. Further ones are a table (lang, classes, words, n_words), or None.
    """
    counts = rows_of(docs, lang=lang_col, text=text_col).where(F.col("lang").isNotNull()).mapInArrow(_partial_counts, "lang string, bin int, word binary, n long")
    counts = written(counts.groupBy("lang", "bin", "word").agg(F.sum("n").alias("n")), "word-counts")
    totals = counts.where((F.col("bin") == _TOTAL_BIN) & (F.col("n") >= MIN_REFERENCE_WORDS)).select("lang", F.col("n").alias("n_words"), (F.col("n") * COMMON_SHARE).alias("least"))
    top = totals.orderBy(F.desc("n_words"), "lang").limit(SENT_LANGUAGES + 1).collect()
    if not top:
        return {}, None
    sent, more = top[:SENT_LANGUAGES], len(top) > SENT_LANGUAGES

    def used(of: DataFrame) -> DataFrame:
        """Character classes and common words of some languages."""
        return counts.join(of, "lang").where((F.col("bin") < _TOTAL_BIN) | ((F.col("bin") == _WORD_BIN) & (F.col("n") >= F.col("least"))))

    n_words = {r.lang: r.n_words for r in sent}
    classes: dict[str, list[int]] = {k: [0] * CLASSES.shape[1] for k in n_words}
    words: dict[str, dict[bytes, int]] = {k: {} for k in n_words}
    for r in used(F.broadcast(docs.sparkSession.createDataFrame([(r.lang, r.least) for r in sent], "lang string, least double"))).collect():
        if r.bin == _WORD_BIN:
            words[r.lang][bytes(r.word)] = r.n
        else:
            classes[r.lang][r.bin] = r.n
    references = {k: Reference(classes[k], words[k], n) for k, n in n_words.items()}
    if not more:
        return references, None
    cells = used(totals.where(~F.col("lang").isin(*n_words))).groupBy("lang").agg(F.first("n_words").alias("n_words"), F.collect_list(F.struct("bin", "word", "n")).alias("cells"))
    class_cells = F.transform(F.array_sort(F.filter("cells", lambda x: x["bin"] < _TOTAL_BIN)), lambda x: x["n"])
    word_cells = F.transform(F.filter("cells", lambda x: x["bin"] == _WORD_BIN), lambda x: F.struct(x["word"].alias("word"), x["n"].alias("n")))
    return references, written(cells.select("lang", class_cells.alias("classes"), word_cells.alias("words"), "n_words"), "references")


def quality_rules(docs: DataFrame, references: dict[str, Reference] | None = None, lang_col: str = "lang", text_col: str = "text") -> DataFrame:
    """Judge each document; add n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, class_distance,
    word_distance, base_failed and kept. Input columns of these names are replaced.

    A null text is empty: it fails the base rules (fewer than 50 words). A document of under MIN_WORDS words, or whose
    language is null or too thin for a reference, gets no verdict from the divergence (null distances) and is kept if
    it passes the base rules. Repeated rows get equal results.
    """
    joined = None
    if references is None:
        references, joined = language_references(docs, lang_col, text_col)
    ref_col = free_name(docs.columns, "reference")

    def kernel():
        seen: dict[str, Reference] = {}

        def joined_reference(lang, row):
            if lang not in seen:
                if len(seen) >= SENT_LANGUAGES:
                    seen.clear()
                row = row.as_py()
                seen[lang] = Reference(row["classes"], {w["word"]: w["n"] for w in row["words"]}, row["n_words"])
            return seen[lang]

        def one(batch):
            out = []
            at = batch.schema.get_field_index(ref_col)
            for k, (lang, raw) in enumerate(zip(batch.column(batch.schema.get_field_index(lang_col)).to_pylist(), texts_of(batch, text_col))):
                words = raw.split()
                n = len(words)
                base = base_counts(raw, words)
                failed = n < 50 or 100 * base[3] > 50 * n
                ref = references.get(lang)
                if at >= 0 and batch.column(at)[k].is_valid:
                    ref = joined_reference(lang, batch.column(at)[k])
                far = ref.distances(raw, words) if ref and n >= MIN_WORDS else (None, None)
                kept = not failed and not (far[0] is not None and (far[0] > MAX_CLASS_DISTANCE or far[1] > MAX_WORD_DISTANCE))
                out.append((n, *base, *far, failed, kept))
            kinds = [pa.int64()] * 5 + [pa.float64()] * 2 + [pa.bool_()] * 2
            return [pa.array(col, type=k) for col, k in zip(zip(*out), kinds)]

        return one

    added = dict.fromkeys(("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"), "long") | {"class_distance": "double", "word_distance": "double", "base_failed": "boolean", "kept": "boolean"}
    if joined is None:
        return mapped(docs, added, kernel)
    own = F.coalesce(F.col(f"`{lang_col}`").isin(*references), F.lit(True))  # sent along, or null
    names = free_name([*docs.columns, ref_col], "reference_lang")
    table = joined.select(F.col("lang").alias(names), F.struct("classes", "words", "n_words").alias(ref_col))
    others = docs.where(~own).join(table, F.col(f"`{lang_col}`") == F.col(names), "left").drop(names)
    return mapped(docs.where(own), added, kernel).unionByName(mapped(others, added, kernel, drop=(ref_col,)))


def op5_quality_rules(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "text")
    return quality_rules(docs).drop("lang", "text", "class_distance", "word_distance")


OP5_SQL = r"""
with d as (select doc_id, lang, coalesce(text, '') as t, list_filter(string_split_regex(coalesce(text, ''), '[ \t\n\x0b\f\r]+'), lambda x: x <> '') as w from documents),
lines as (select doc_id, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ \t\n\x0b\f\r]')) as l from d),
win as (select doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as g from (select doc_id, w, unnest(range(1, greatest(len(w) - 1, 1))) as i from d) x where w[i + 2] is not null),
dup as (select doc_id, i from win where (doc_id, g) in (select (doc_id, g) from win group by doc_id, g having count(*) > 1)),
rep as (select doc_id, count(distinct i + k) as n from dup, range(3) r(k) group by doc_id),
base as (select d.doc_id, lang, t, w, len(w)::bigint as n_words, length(regexp_replace(t, '[ \t\n\x0b\f\r]', '', 'g'))::bigint as word_chars,
  (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols, (len(l) - len(list_distinct(l)))::bigint as n_dup_lines, coalesce(rep.n, 0)::bigint as n_repeat_words
  from d join lines using (doc_id) left join rep using (doc_id)),
cls as (select doc_id, lang, k, (length(t) - length(regexp_replace(t, p, '', 'g')))::double as n from d,
  (values (0, '[a-z]'), (1, '[A-Z]'), (2, '[0-9]'), (3, '[ \t\n\x0b\f\r]'), (4, '[.,;:!?''"()\-]'), (5, '[\x00-\x08\x0e-\x1f#$%&*+/<=>@\[\\\]^_`{|}~\x7f]'), (6, '[^\x00-\x7f]')) c(k, p)),
cref as (select lang, k, sum(n) as n from cls group by all),
words as (select doc_id, lang, unnest(w) as w from d),
lw as (select lang, w, count(*) as n from words group by all),
common as (select lang, w, n from (select *, sum(n) over (partition by lang) as total from lw) x where n >= 0.002 * total),
wd as (select doc_id, lang, coalesce(c.w, '') as b, count(*)::double as n from words left join common c using (lang, w) group by all),
wref as (select lang, coalesce(c.w, '') as b, sum(lw.n)::double as n from lw left join common c using (lang, w) group by all),
cp as (select c.doc_id, c.n / sum(c.n) over (partition by c.doc_id) as p, r.n / sum(r.n) over (partition by c.doc_id) as q from cls c join cref r using (lang, k)),
cdist as (select doc_id, sqrt(greatest(sum(DIVERGENCE), 0) / 2) as x from cp group by doc_id),
wp as (select x.doc_id, coalesce(wd.n, 0) / sum(wd.n) over (partition by x.doc_id) as p, r.n / sum(r.n) over (partition by x.doc_id) as q from d x join wref r using (lang) left join wd on wd.doc_id = x.doc_id and wd.b = r.b),
wdist as (select doc_id, sqrt(greatest(sum(DIVERGENCE), 0) / 2) as x from wp group by doc_id)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (n_words < 50 or 100 * n_repeat_words > 50 * n_words) as base_failed,
  not (n_words < 50 or 100 * n_repeat_words > 50 * n_words) and (judged.lang is null or n_words < MIN_WORDS or (cdist.x <= 0.3 and wdist.x <= 0.5)) as kept
from base left join cdist using (doc_id) left join wdist using (doc_id) left join (select lang from lw where lang is not null group by lang having sum(n) >= MIN_REFERENCE_WORDS) judged using (lang)
""".replace("DIVERGENCE", "(case when p > 0 then p * log2(p / ((p + q) / 2)) else 0 end + case when q > 0 then q * log2(q / ((p + q) / 2)) else 0 end)").replace("MIN_WORDS", str(MIN_WORDS)).replace("MIN_REFERENCE_WORDS", str(MIN_REFERENCE_WORDS))
