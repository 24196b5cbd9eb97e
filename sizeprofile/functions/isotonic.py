"""Isotonic fits: exact kernels for both norms, per node and, for nodes too large for one task, in chunks."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pooled_means(sums: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators over weighted blocks: (sums, weights) of the resulting blocks, means strictly ascending."""
    s: list[float] = []
    w: list[float] = []
    for a, b in zip(sums.tolist(), weights.tolist()):
        s.append(a)
        w.append(b)
        while len(s) > 1 and s[-2] * w[-1] >= s[-1] * w[-2]:
            a, b = s.pop(), w.pop()
            s[-1] += a
            w[-1] += b
    return np.array(s), np.array(w)


def isotonic_l2(values, lo: float | None = None, hi: float | None = None) -> np.ndarray:
    """The non-decreasing sequence nearest in squares, clipped to [lo, hi] (which keeps it optimal under the bounds)."""
    x = np.asarray(values, dtype=float)
    s, w = pooled_means(x, np.ones(len(x)))
    return np.clip(np.repeat(s / w if len(w) else s, w.astype(np.int64)), lo, hi) if lo is not None or hi is not None else np.repeat(s / w if len(w) else s, w.astype(np.int64))


def isotonic_l1(values, lo=None, hi=None) -> np.ndarray:
    """The smallest of the non-decreasing sequences nearest in absolute values; whole numbers stay whole.

    One pass keeps, in a heap, the break points of the best cost as a function of the last value: where a new value is
    below the largest break point, that one moves down to it. Going back, each value is capped by its successor.
    """
    x = np.asarray(values)
    top, heap = [], []
    for v in x.tolist():
        heapq.heappush(heap, -v)
        if -heap[0] > v:
            heapq.heapreplace(heap, -v)
        top.append(-heap[0])
    out = np.minimum.accumulate(np.array(top, dtype=x.dtype)[::-1])[::-1] if top else x
    return np.clip(out, lo, hi) if lo is not None or hi is not None else out


def isotonic(values, p: int, lo=None, hi=None) -> np.ndarray:
    return isotonic_l1(values, lo, hi) if p == 1 else isotonic_l2(values, lo, hi)


def isotonic_minmax(values, p: int) -> np.ndarray:
    """Independent form: largest, over left ends, of the smallest, over right ends, interval value. Cubic; for tests."""
    x = np.asarray(values, dtype=float)
    n = len(x)
    value = (lambda a: a.mean()) if p == 2 else (lambda a: np.sort(a)[(len(a) - 1) // 2])
    return np.array([max(min(value(x[a : r + 1]) for r in range(i, n)) for a in range(i + 1)) for i in range(n)])


def fit_by_node(df: DataFrame, keys: list[str], order: list[str], value: str, p: int, carry: list[str] = ()) -> DataFrame:
    """Fit each group's values in the given order; returns keys, order columns, carried columns and `fit`."""
    kept = [*keys, *order, *carry]
    schema = df.select(*kept, F.col(value).cast("double").alias("fit")).schema

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(order, kind="stable")
        return pdf[kept].assign(fit=isotonic(pdf[value].to_numpy(), p).astype(float))

    return df.select(*kept, value).groupBy(*keys).applyInPandas(fit, schema)


def lower_median(values: np.ndarray, counts: np.ndarray) -> float:
    """Of a multiset given by its ascending distinct values and their counts."""
    upto = np.cumsum(counts)
    return values[np.searchsorted(upto, (upto[-1] - 1) // 2, side="right")]


def pooled_medians(blocks: list[tuple[np.ndarray, np.ndarray]]) -> tuple[list[float], np.ndarray]:
    """Pool adjacent violators over blocks of (ascending values, counts): strictly ascending lower medians, and the first block of each pool."""
    held: list[tuple[float, np.ndarray, np.ndarray]] = []
    first: list[int] = []
    for k, (values, counts) in enumerate(blocks):
        held.append((lower_median(values, counts), values, counts))
        first.append(k)
        while len(held) > 1 and held[-2][0] >= held[-1][0]:
            _, v1, c1 = held.pop()
            _, v0, c0 = held.pop()
            first.pop()
            both, place = np.unique(np.r_[v0, v1], return_inverse=True)
            counts = np.bincount(place, weights=np.r_[c0, c1]).astype(np.int64)
            held.append((lower_median(both, counts), both, counts))
    return [h[0] for h in held], np.array(first, dtype=np.int64)


def pooled_stretches(df: DataFrame, keys: list[str], order: list[str], stretch: list[str], value: str, p: int) -> DataFrame:
    """The fit of groups of any size: (keys, order columns of the first row, cnt, fit) blocks.

    Rows of equal (keys, stretch) must stand in one partition in ascending order; stretches follow each other in `order`.
    A task pools the violators of its stretches batch by batch, a row at a time is never shuffled, and only blocks meet by keys, where
    pooling them gives the same fit as pooling the rows. A block is its count and total for squares, and the
    histogram of its values for absolute gaps.
    """
    shape = df.select(*keys, *order).schema
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in shape)

    def local(batches):
        for pdf in batches:
            kept, cnt, total, values, counts = [], [], [], [], []
            x = pdf[value].to_numpy()
            for rows in pdf.groupby([*keys, *stretch], sort=False, dropna=False).indices.values():
                part = x[rows]
                if p == 2:
                    s, w = pooled_means(part, np.ones(len(part)))
                    first = np.r_[0, np.cumsum(w)[:-1]].astype(np.int64)
                    total += s.tolist()
                else:
                    fit = isotonic_l1(part)
                    first = np.flatnonzero(np.r_[True, fit[1:] != fit[:-1]])
                    for a, b in zip(first, [*first[1:], len(part)]):
                        v, c = np.unique(part[a:b], return_counts=True)
                        values.append(v.astype(float).tolist())
                        counts.append(c.tolist())
                kept.append(rows[first])
                cnt += np.diff(np.r_[first, len(part)]).tolist()
            if kept:
                out = pdf.iloc[np.concatenate(kept)][[*keys, *order]].reset_index(drop=True)
                yield out.assign(cnt=cnt, total=total if p == 2 else 0.0, vals=None if p == 2 else pd.Series(values, dtype=object), counts=None if p == 2 else pd.Series(counts, dtype=object))

    def final(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(order, kind="stable")
        n = pdf["cnt"].to_numpy()
        if p == 2:
            s, w = pooled_means(pdf["total"].to_numpy(), n.astype(float))
            ends = np.searchsorted(np.cumsum(n), np.cumsum(w) - 0.5)
            first, fit = np.r_[0, ends[:-1] + 1].astype(np.int64), s / w
        else:
            fit, first = pooled_medians([(np.asarray(v), np.asarray(c)) for v, c in zip(pdf["vals"], pdf["counts"])])
        return pdf.iloc[first][[*keys, *order]].assign(cnt=np.add.reduceat(n, first), fit=np.asarray(fit, dtype=float))

    pooled = df.select(*dict.fromkeys([*keys, *order, *stretch]), value).mapInPandas(local, f"{fields}, cnt long, total double, vals array<double>, counts array<long>")
    return pooled.groupBy(*keys).applyInPandas(final, f"{fields}, cnt long, fit double")


def fit_chunked(df: DataFrame, keys: list[str], order: list[str], value: str, chunks: int, p: int = 2) -> DataFrame:
    """The same for rows in any order: they are dealt by ranges of (keys, order), so no task holds a whole large group."""
    ranked = df.select(*keys, *order, F.col(value).cast("double").alias(value)).repartitionByRange(chunks, *keys, *order).sortWithinPartitions(*keys, *order)
    return pooled_stretches(ranked, keys, order, [], value, p)
