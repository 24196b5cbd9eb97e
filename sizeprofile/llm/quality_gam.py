"""Quality classifier: a generalised additive model with pairwise interactions, boosted from shallow trees.

The model is a lookup table for each feature and for each chosen pair of features; a score is the logistic of the sum
of one entry of each. Inputs are measures of the text alone.
"""

from __future__ import annotations

from collections import Counter
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE, mapped, rows_of, texts_of, written
from .quality_rules import base_counts

FEATURES = ("log_words", "word_length", "long_words", "short_words", "symbols", "bars", "punctuation", "digits", "upper", "non_ascii", "spaces", "duplicate_lines", "repeated_words", "distinct_words", "top_word", "log_lines", "line_words", "capital_words", "bare_words", "byte_entropy")
#: Labelled rows fitted on, chosen by a hash over the whole table.
MAX_LABELLED_ROWS = 20_000
BINS, PAIR_BINS, PAIRS = 32, 8, 6
ROUNDS, PAIR_ROUNDS, RATE, LEAVES = 150, 60, 0.1, 3

_UPPER, _DIGITS, _PUNCTUATION = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:!?'\"()-"
_LETTERS = b"abcdefghijklmnopqrstuvwxyz" + _UPPER + bytes(range(0x80, 0x100))


def measures(raw: bytes) -> list[float]:
    """The features of one text; all are defined for an empty text."""
    words = raw.split()
    n, size, lines = len(words), max(1, len(raw)), raw.count(b"\n") + 1
    if not n:
        return [0.0] * len(FEATURES)
    _, symbols, doubled, repeated = base_counts(raw, words)
    length = np.fromiter(map(len, words), dtype=np.int64, count=n)
    seen = Counter(words)
    share = np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256) / size
    some = share[share > 0]
    count = lambda group: float(share[list(group)].sum())
    caps = sum(map(bytes.istitle, words))
    bare = sum(not w.strip(_PUNCTUATION).strip(_LETTERS) for w in words)
    return [np.log1p(n), float(length.mean()), float((length > 12).mean()), float((length <= 3).mean()), symbols / size, float(share[124]), count(_PUNCTUATION), count(_DIGITS), count(_UPPER), float(share[128:].sum()), count(SPACE), doubled / lines, repeated / n, len(seen) / n, seen.most_common(1)[0][1] / n, np.log(lines), n / lines, caps / n, bare / n, float(-(some * np.log2(some)).sum())]


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and x, its features as 32-bit floats (binary). A null text is empty."""

    def kernel():
        return lambda batch: [pa.array([np.array(measures(t), dtype="<f4").tobytes() for t in texts_of(batch, "text")], type=pa.binary())]

    return mapped(rows_of(docs, doc_id=F.col(f"`{id_col}`"), text=text_col), {"x": "binary"}, kernel, drop=("text",))


class Gam:
    """cuts[f]: bin borders of feature f; tables[f]: its entries; pairs: (f, g, table over coarse bins of both)."""

    def __init__(self, intercept: float, cuts: list[np.ndarray], tables: list[np.ndarray], coarse: list[np.ndarray], pairs: list[tuple[int, int, np.ndarray]]):
        self.intercept, self.cuts, self.tables, self.coarse, self.pairs = intercept, cuts, tables, coarse, pairs

    def scores(self, x: np.ndarray) -> np.ndarray:
        """Vectorised: look up each feature's bin, add the entries."""
        total = np.full(len(x), self.intercept)
        codes = [np.searchsorted(c, x[:, f], side="right") for f, c in enumerate(self.cuts)]
        for table, code in zip(self.tables, codes):
            total += table[code]
        for f, g, table in self.pairs:
            total += table[self.coarse[f][codes[f]], self.coarse[g][codes[g]]]
        return 1 / (1 + np.exp(-np.clip(total, -40, 40)))


def _step_table(g: np.ndarray, h: np.ndarray, leaves: int) -> np.ndarray:
    """A shallow regression tree over ordered bins: split the piece that gains most until there are `leaves`; Newton steps in the leaves."""
    gain = lambda a, b: a * a / (b + 1.0)
    cg, ch = np.r_[0, np.cumsum(g)], np.r_[0, np.cumsum(h)]

    def best(lo, hi):
        if hi - lo < 2:
            return (0.0, lo, lo, hi)
        k = np.arange(lo + 1, hi)
        got = gain(cg[k] - cg[lo], ch[k] - ch[lo]) + gain(cg[hi] - cg[k], ch[hi] - ch[k]) - gain(cg[hi] - cg[lo], ch[hi] - ch[lo])
        j = int(np.argmax(got))
        return (float(got[j]), int(k[j]), lo, hi)

    pieces = [best(0, len(g))]
    while len(pieces) < leaves and max(pieces)[0] > 1e-9:
        _, k, lo, hi = top = max(pieces)
        pieces.remove(top)
        pieces += [best(lo, k), best(k, hi)]
    out = np.zeros(len(g))
    for _, _, lo, hi in pieces:
        out[lo:hi] = (cg[hi] - cg[lo]) / (ch[hi] - ch[lo] + 1.0)
    return out


def _step_quadrants(g: np.ndarray, h: np.ndarray) -> tuple[float, np.ndarray]:
    """The best cut of both features of a pair: (gain, Newton steps of the four quadrants)."""
    cg, ch = g.cumsum(0).cumsum(1), h.cumsum(0).cumsum(1)
    quads = []
    for c in (cg, ch):
        a, top, side, whole = c[:-1, :-1], c[:-1, -1:], c[-1:, :-1], c[-1, -1]
        quads.append(np.stack([a, top - a, side - a, whole - top - side + a]))
    gains = (quads[0] ** 2 / (quads[1] + 1.0)).sum(0)
    i, j = np.unravel_index(int(np.argmax(gains)), gains.shape)
    step = (quads[0] / (quads[1] + 1.0))[:, i, j]
    out = np.empty_like(g)
    out[: i + 1, : j + 1], out[: i + 1, j + 1 :], out[i + 1 :, : j + 1], out[i + 1 :, j + 1 :] = step
    return float(gains[i, j]), out


def fit_gam(x: np.ndarray, y: np.ndarray) -> Gam:
    """Cyclic boosting: each round gives every feature in turn one small tree on the current residuals; then pairs likewise.

    Too few rows or a single class: no tables, only the base rate.
    """
    rate = (y.sum() + 1) / (len(y) + 2)
    start = float(np.log(rate / (1 - rate)))
    cuts = [np.unique(np.quantile(col, np.linspace(0, 1, BINS + 1)[1:-1])) if len(y) else np.zeros(0) for col in x.T]
    codes = [np.searchsorted(c, col, side="right") for c, col in zip(cuts, x.T)]
    tables = [np.zeros(len(c) + 1) for c in cuts]
    coarse = [np.arange(len(c) + 1) * PAIR_BINS // (len(c) + 1) for c in cuts]
    pairs: list[tuple[int, int, np.ndarray]] = []
    if len(y) < 50 or y.min() == y.max():
        return Gam(start, cuts, tables, coarse, pairs)
    total = np.full(len(y), start)

    def residuals():
        p = 1 / (1 + np.exp(-total))
        return y - p, p * (1 - p)

    for _ in range(ROUNDS):
        for f, code in enumerate(codes):
            g, h = residuals()
            n = len(tables[f])
            step = RATE * _step_table(np.bincount(code, g, n), np.bincount(code, h, n), LEAVES)
            tables[f] += step
            total += step[code]

    def grid(f, g_):
        cell = coarse[f][codes[f]] * PAIR_BINS + coarse[g_][codes[g_]]
        return cell, *(np.bincount(cell, v, PAIR_BINS**2).reshape(PAIR_BINS, PAIR_BINS) for v in residuals())

    ranked = sorted(((_step_quadrants(*grid(f, g)[1:])[0], f, g) for f, g in combinations(range(x.shape[1]), 2)), reverse=True)[:PAIRS]
    pairs = [(f, g, np.zeros((PAIR_BINS, PAIR_BINS))) for _, f, g in ranked]
    for _ in range(PAIR_ROUNDS):
        for f, g_, table in pairs:
            cell, g, h = grid(f, g_)
            step = RATE * _step_quadrants(g, h)[1]
            table += step
            total += step.reshape(-1)[cell]
    return Gam(start, cuts, tables, coarse, pairs)


def held_out(id_col: str) -> F.Column:
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % 5 == 0


def labelled_sample(table: DataFrame, labels: DataFrame, label_col: str, most: int = MAX_LABELLED_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """At most `most` labelled rows outside the held-out fold, spread over the whole table by a hash of the id."""
    known = rows_of(labels, doc_id="doc_id", y=label_col).where(F.col("y").isNotNull() & F.col("doc_id").isNotNull() & ~held_out("doc_id"))
    share = min(1.0, most / max(1, known.count()))
    known = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(share * 1_000_000))
    rows = table.join(known, "doc_id").select("x", "y").limit(most).toArrow() if share else None
    x = np.frombuffer(b"".join(rows.column("x").to_pylist()), dtype="<f4").reshape(-1, len(FEATURES)).astype(float)
    return x, rows.column("y").to_numpy().astype(float)


def score_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = 0.3) -> DataFrame:
    """doc_id, held_out, score and predicted for every row of `docs`.

    Null and empty texts are scored from an all-zero feature row. Repeated rows get equal scores. Without labels of
    both classes the score is the base rate (one half without any label).
    """
    table = written(measured(docs, id_col, text_col), "measures")
    gam = fit_gam(*labelled_sample(table, labels, "quality"))

    def kernel():
        return lambda batch: [pa.array(gam.scores(np.frombuffer(b"".join(batch.column(batch.schema.get_field_index("x")).to_pylist()), dtype="<f4").reshape(-1, len(FEATURES)).astype(float)))]

    scored = mapped(table, {"score": "double"}, kernel, drop=("x",))
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", F.when(F.col("score") >= least, 1).otherwise(0).alias("predicted"))


def op10_quality_gam(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return score_quality(docs, spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality"))
