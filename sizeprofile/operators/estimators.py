"""Single-node estimators: naive cell noise, sorted sizes (hg) and cumulative counts (hc).

All take the exact histogram of many nodes and a small table of runs (run_id, seed, eps: budget of a level), and
return (run_id, level, node_id, size, cnt) of every run and node in one job. Noise keys are (seed, level:node, cell).
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.isotonic import isotonic, pooled_means, pooled_stretches
from ..functions.noise import SENSITIVITY, geometric_faces, geometric_noise, keyed_generator
from . import profile

KEYS = ("run_id", "level", "node_id")


def each_node(cells: DataFrame, kernel: Callable[[tuple, dict[str, np.ndarray]], tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """(keys, size, cnt): the `kernel` of each node of a run gets its keys and its columns in the order of sizes, and returns sizes and counts.

    Nodes are dealt over all cores and cut from sorted batches: a sweep has thousands of small ones, and as groups of Spark each
    would cost a frame and a message, which is more than its fit. A node that goes on in the next batch waits for its end.
    """

    def run(batches):
        key, parts = None, []

        def closed():
            return key, *kernel(key, {c: np.concatenate([p[c] for p in parts]) for c in parts[0]})

        def frame(done):
            lengths = [len(cnt) for _, _, cnt in done]
            keys = {k: np.repeat(np.array([d[0][i] for d in done]), lengths) for i, k in enumerate(KEYS)}
            return pd.DataFrame({**keys, "size": np.concatenate([d[1] for d in done]), "cnt": np.concatenate([d[2] for d in done])})

        for pdf in batches:
            columns, done = {c: pdf[c].to_numpy() for c in pdf.columns}, []
            cuts = [0, *(np.flatnonzero(np.logical_or.reduce([columns[k][1:] != columns[k][:-1] for k in KEYS])) + 1).tolist(), len(pdf)] if len(pdf) else []
            for a, b in zip(cuts, cuts[1:]):
                now = tuple(columns[k][a] for k in KEYS)
                if parts and now != key:
                    done.append(closed())
                    parts = []
                key = now
                parts.append({c: v[a:b] for c, v in columns.items()})
            if done:
                yield frame(done)
        if parts:
            yield frame([closed()])

    return cells.sortWithinPartitions(*KEYS, "size").mapInPandas(run, "run_id int, level int, node_id string, size long, cnt long")


def runs_table(spark, runs: list[tuple[int, str, float]]) -> DataFrame:
    return F.broadcast(spark.createDataFrame(runs, "run_id int, seed string, eps double"))  # one row a release


def _noisy(cells: DataFrame, method: str, *cell: str) -> DataFrame:
    scale = F.lit(float(SENSITIVITY[method])) / F.col("eps")
    return cells.withColumn("noise", geometric_noise(scale, F.col("seed"), F.col("level"), F.col("node_id"), *[F.col(c) for c in cell]))


def project_simplex(cells: DataFrame, total: str = "g", value: str = "x", keys: tuple[str, ...] = KEYS) -> DataFrame:
    """Nearest point with non-negative cells that sum to `total`: all cells less one threshold, cut at zero."""
    w = Window.partitionBy(*keys).orderBy(F.desc(value), "size")
    ranked = cells.withColumn("rank", F.row_number().over(w)).withColumn("running", F.sum(value).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    theta = F.when(F.col(value) - (F.col("running") - F.col(total)) / F.col("rank") > 0, (F.col("running") - F.col(total)) / F.col("rank"))
    last = F.max_by(theta, F.when(theta.isNotNull(), F.col("rank"))).over(Window.partitionBy(*keys))
    return ranked.withColumn("theta", last).withColumn("projected", F.when(F.col(total) <= 0, 0.0).otherwise(F.greatest(F.col(value) - F.col("theta"), F.lit(0.0)))).drop("rank", "running", "theta")


def round_largest_remainder(cells: DataFrame, value: str = "projected", total: str = "g", keys: tuple[str, ...] = KEYS) -> DataFrame:
    """Whole numbers that keep the total: floors, and one more for the largest remainders (ties: the smaller size)."""
    low = F.floor(F.round(F.col(value), 9))
    w = Window.partitionBy(*keys)
    rank = F.row_number().over(w.orderBy(F.desc(F.round(F.col(value) - low, 9)), "size"))
    return cells.withColumn("short", F.col(total) - F.sum(low).over(w)).withColumn("cnt", (low + F.when(rank <= F.col("short"), 1).otherwise(0)).cast("long")).drop("short")


def naive_cells(hist: DataFrame, counts: DataFrame, runs: DataFrame, ceiling: int) -> DataFrame:
    """Every cell 0 .. ceiling with noise: (keys, size, g, x)."""
    grid = counts.select("level", "node_id", "g", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(ceiling).cast("long"))).alias("size"))
    known = profile.clamp_sizes(hist, ceiling).groupBy("level", "node_id", "size").agg(F.sum("cnt").alias("cnt"))
    cells = grid.join(known, ["level", "node_id", "size"], "left").crossJoin(runs)
    return _noisy(cells, "naive", "size").select(*KEYS, "size", "g", (F.coalesce("cnt", F.lit(0)) + F.col("noise")).cast("double").alias("x"))


def estimate_naive(hist: DataFrame, counts: DataFrame, runs: DataFrame, ceiling: int) -> DataFrame:
    return round_largest_remainder(project_simplex(naive_cells(hist, counts, runs, ceiling))).where("cnt > 0").select(*KEYS, "size", "cnt")


def cumulative_cells(hist: DataFrame, counts: DataFrame, runs: DataFrame, ceiling: int) -> DataFrame:
    """Noisy running counts of sizes 0 .. ceiling - 1 (the last is the public count and gets no noise), a node of a run in one task."""
    cum = profile.to_cumulative(hist, counts, ceiling).where(F.col("size") < ceiling).join(counts, ["level", "node_id"]).crossJoin(runs)
    return _noisy(profile.dealt(cum, *KEYS), "hc", "size").select(*KEYS, "size", "g", (F.col("cum") + F.col("noise")).cast("long").alias("noisy"))


def estimate_cumulative(hist: DataFrame, counts: DataFrame, runs: DataFrame, ceiling: int, p: int = 1) -> DataFrame:
    """Isotonic fit of the noisy running counts, within 0 .. g and ending at g, rounded and differenced.

    A node's cells meet in one kernel, which is bounded by the ceiling; only the cells that are left come back.
    """

    def release(_, node: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        g = int(node["g"][0])
        upto = np.floor(np.clip(isotonic(node["noisy"], p).astype(float), 0, g) + 0.5).astype(np.int64)
        cnt = np.diff(np.r_[0, upto, g])
        some = np.flatnonzero(cnt)
        return np.r_[node["size"], ceiling][some], cnt[some]

    return each_node(cumulative_cells(hist, counts, runs, ceiling), release)


def sorted_cells(hist: DataFrame, runs: DataFrame, block_rows: int = profile.BLOCK_ROWS) -> DataFrame:
    """One noisy size a group, keyed by (size, place j among equals): (keys, size, block, j, noisy). Ranks are not needed.

    Places of equal size are dealt in blocks, so that a size that very many groups have is no single task.
    """
    rows = profile.exploded(hist.where("cnt > 0").select("level", "node_id", "size", F.lit(1).cast("long").alias("first"), "cnt"), "j", block_rows).crossJoin(runs)
    return _noisy(rows, "hg", "size", "j").select(*KEYS, "size", "block", "j", (F.col("size") + F.col("noise")).cast("long").alias("noisy"))


def estimate_sorted(hist: DataFrame, runs: DataFrame, p: int = 2, by_fit: bool = False, block_rows: int = profile.BLOCK_ROWS) -> DataFrame:
    """Isotonic fit of the noisy sorted sizes, floored at 0, rounded, counted. Only pooled blocks of groups are shuffled.

    `by_fit` counts groups by their fitted value before rounding (one row a block of equal fits).
    """
    blocks = pooled_stretches(sorted_cells(hist, runs, block_rows), [*KEYS], ["size", "j"], ["size", "block"], "noisy", p).select(*KEYS, "cnt", "fit")
    size = F.floor(F.greatest(F.col("fit"), F.lit(0.0)) + 0.5).cast("long").alias("size")
    if by_fit:
        return blocks.groupBy(*KEYS, "fit").agg(F.sum("cnt").alias("cnt")).select(*KEYS, size, "cnt")
    return blocks.groupBy(*KEYS, size).agg(F.sum("cnt").alias("cnt"))


def estimate_sorted_faces(hist: DataFrame, runs: DataFrame) -> DataFrame:
    """`estimate_sorted` in squares, equal in law, for experiments: draws and rows follow distinct sizes, not groups.

    The groups of one size are drawn as the blocks of their own fit (`geometric_faces`), and the blocks of a node's sizes are
    pooled as they are there. The noise is another draw than the one keyed by places.
    """

    def release(key: tuple, node: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        rng = keyed_generator(node["seed"][0], *key[1:], "faces")
        scale = SENSITIVITY["hg"] / node["eps"][0]
        faces = [geometric_faces(n, size, scale, rng) for size, n in zip(node["size"].tolist(), node["cnt"].tolist())]
        s, w = pooled_means(np.concatenate([t for t, _ in faces]).astype(float), np.concatenate([c for _, c in faces]).astype(float))
        size, place = np.unique(np.floor(np.maximum(s / w, 0.0) + 0.5).astype(np.int64), return_inverse=True)
        return size, np.bincount(place, weights=w).astype(np.int64)

    cells = hist.where("cnt > 0").select("level", "node_id", "size", "cnt").crossJoin(runs)
    return each_node(profile.dealt(cells, *KEYS), release)


def estimate(method: str, hist: DataFrame, counts: DataFrame, runs: DataFrame, ceiling: int, p_c: int = 1, p_g: int = 2, by_fit: bool = False) -> DataFrame:
    if method == "hc":
        return estimate_cumulative(hist, counts, runs, ceiling, p_c)
    if method == "hg":
        return estimate_sorted(hist, runs, p_g, by_fit=by_fit)
    if method == "naive":
        return estimate_naive(hist, counts, runs, ceiling)
    raise ValueError(f"unknown method {method}")


def estimate_tree(hist: DataFrame, counts: DataFrame, runs: DataFrame, ceiling: int, methods: list[str], p_c: int = 1, p_g: int = 2, by_fit: bool = False) -> DataFrame:
    """One method a level; levels that share a method are fitted in one job. Adds the column `method`."""
    out = None
    for m in dict.fromkeys(methods):
        at = [k for k, x in enumerate(methods) if x == m]
        part = estimate(m, hist.where(F.col("level").isin(at)), counts.where(F.col("level").isin(at)), runs, ceiling, p_c, p_g, by_fit).withColumn("method", F.lit(m))
        out = part if out is None else out.unionByName(part)
    return out


def variance(estimates: DataFrame, runs: DataFrame, exact: bool = False) -> DataFrame:
    """Add `var`, the estimated variance of a group's size: from the run of equal sizes (hg) or the size's count (hc).

    `exact` puts the variance of the geometric noise for its approximation 2 / eps^2.
    """
    a = F.exp(-F.col("eps"))
    unit = (2 * a / ((1 - a) * (1 - a))) if exact else F.lit(2.0) / (F.col("eps") * F.col("eps"))
    return estimates.join(runs, "run_id").withColumn("var", F.when(F.col("method") == "hg", unit / F.col("cnt")).otherwise(F.lit(2.0) * unit / F.col("cnt"))).drop("seed", "eps")


def estimate_ceiling(sizes: DataFrame, seed: str, eps: float = 1e-4) -> DataFrame:
    """A private ceiling: noisy maximum plus five standard deviations of the noise. Its budget is extra."""
    from ..functions.noise import laplace_noise

    scale = 1.0 / eps
    return sizes.agg(F.max("size").alias("top")).select((F.ceil(F.col("top") + laplace_noise(scale, seed, "ceiling") + F.lit(5 * scale * 2**0.5))).cast("long").alias("ceiling"))
