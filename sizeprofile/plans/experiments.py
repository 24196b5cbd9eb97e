"""The experiments: every workload, method, baseline and parameter sweep as one report frame.

All seeds and budgets of a sweep are rows of one small table, so a sweep scans the data once. Sorted sizes are drawn by their
law, in which a size costs about the logarithm of its groups: ten seeds a budget would else draw hundreds of noises a group.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import estimators, metrics, profile
from ..operators.tree import RegionTree
from ..sources.synthetic_tail import extend_tail
from ..sources.workloads import WORKLOADS
from . import release

SEEDS, GRID = 10, (0.05, 0.1, 0.2, 0.5, 1.0)
Release = Callable[[DataFrame, DataFrame, RegionTree, DataFrame], DataFrame]


def tail_workload(spark, sf_dir: str, seed: str = "tail") -> tuple[DataFrame, RegionTree]:
    """Order sizes cut at 7 and extended by a synthetic tail and outliers."""
    entities, groups, tree = WORKLOADS["w1"].load(spark, sf_dir)
    region = tree.wide.select("leaf_id", F.col("level_1").alias("region"))
    return extend_tail(profile.group_sizes(entities, groups), tree.small(region), seed), tree


def inputs(spark, sf_dir: str, workload: str, ceiling: int | None = None, levels: int | None = None, nodes: list[str] | None = None) -> tuple[DataFrame, DataFrame, RegionTree, int]:
    """(exact histogram, public counts, tree, ceiling); `levels` cuts the tree, `nodes` restricts its root.

    The tables are read once: tree and counts come from the leaves' histogram, in which every public group counts once.
    """
    if workload == "w2":
        sizes, tree = tail_workload(spark, sf_dir)
        columns, ceiling = [], ceiling or 10_240
    else:
        w = WORKLOADS[workload]
        sizes, tree = profile.group_sizes(w.query(spark, sf_dir, w.entities), w.placed(spark, sf_dir)), None
        columns, ceiling = list(w.levels), ceiling or w.ceiling
    cells = release.frozen(profile.clamp_sizes(sizes, ceiling).groupBy("leaf_id", *columns, "size").agg(F.count(F.lit(1)).alias("cnt")))
    tree = tree or RegionTree.from_levels(cells, columns)
    tree = tree.restrict(nodes) if nodes else tree
    tree = RegionTree(release.frozen(tree.wide), tree.levels)
    leaves = cells.groupBy("leaf_id", "size").agg(F.sum("cnt").alias("cnt"))
    hist = release.frozen(profile.rollup_histogram(leaves, tree))
    counts = release.frozen(profile.summed_counts(leaves.groupBy("leaf_id").agg(F.sum("cnt").alias("n")), tree))
    if levels and levels < tree.levels:
        last = levels - 1
        tree = RegionTree(tree.wide.select(*[f"level_{k}" for k in range(levels)]).distinct().withColumn("leaf_id", F.col(f"level_{last}")), levels)
        hist, counts = hist.where(F.col("level") <= last), counts.where(F.col("level") <= last)
        tree = RegionTree(release.frozen(tree.wide), tree.levels)
    return hist, counts, tree, ceiling


def run_grid(spark, eps: tuple[float, ...], seeds: int) -> tuple[DataFrame, DataFrame]:
    """(runs, run_id -> eps): one row a seed and budget of a level."""
    rows = [(i * seeds + k, f"seed{k}", e) for i, e in enumerate(eps) for k in range(seeds)]
    return estimators.runs_table(spark, rows), F.broadcast(spark.createDataFrame([(r, e) for r, _, e in rows], "run_id int, eps_level double"))


def evaluate(spark, hist: DataFrame, counts: DataFrame, tree: RegionTree, releases: dict[str, Release], eps: tuple[float, ...], seeds: int, measured: tuple[int, ...] | None = None) -> DataFrame:
    """(method, eps_level, eps_total, level, emd, std_of_mean, runs), the error being the mean over a level's nodes."""
    runs, budgets = run_grid(spark, eps, seeds)
    truth = metrics.for_runs(hist, runs)
    wanted = dict.fromkeys(x for make in releases.values() for x in getattr(make, "estimates", ()))
    shared = {m: release.frozen(profile.gathered(estimators.estimate_sorted_faces(hist, runs) if m == "hg" else estimators.estimate(m, hist, counts, runs, k))) for m, k in wanted}  # releases that start from equal estimates share them
    out = None
    for name, make in releases.items():
        rel = make(hist, counts, tree, runs, shared) if hasattr(make, "estimates") else make(hist, counts, tree, runs)
        report = metrics.level_report(metrics.emd(truth if measured is None else truth.where(F.col("level").isin(*measured)), rel), counts if measured is None else counts.where(F.col("level").isin(*measured)), runs)
        done = metrics.run_report(report.join(budgets, "run_id"), "eps_level").select(F.lit(name).alias("method"), "eps_level", (F.col("eps_level") * tree.levels).alias("eps_total"), "level", "emd", "std_of_mean", "runs")
        done = release.frozen(done)  # a few rows; a union of whole plans would be planned anew after each of its stages
        out = done if out is None else out.unionByName(done)
    expected = metrics.level_report(metrics.omniscient_expected(hist, runs), counts, runs).join(budgets, "run_id")
    return out.unionByName(release.frozen(metrics.run_report(expected, "eps_level")).select(F.lit("omniscient").alias("method"), "eps_level", (F.col("eps_level") * tree.levels).alias("eps_total"), "level", "emd", "std_of_mean", "runs"))


def _topdown(ceiling: int, methods="hc", **kw) -> Release:
    def make(h, c, t, r, estimates):
        return release.release_topdown(h, c, t, r, methods, ceiling, estimates=estimates, **kw)

    make.estimates = [(m, ceiling) for m in ([methods] if isinstance(methods, str) else methods)]
    return make


def _bottom_up(ceiling: int) -> Release:
    def make(h, c, t, r):  # the whole budget at the leaves
        return release.release_bottom_up(h, c, t, F.broadcast(r.withColumn("eps", F.col("eps") * t.levels)), "hc", ceiling)

    return make


def _named(df: DataFrame, **values) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in values.items()], "*")


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def _beside(spark, jobs: list[Callable[[], DataFrame]], at_once: int = 2) -> DataFrame:
    """The union of the jobs' frames; some run beside each other, as each is many small stages one after another (with four, one of w2 ran out of memory at sf0.1)."""
    with ThreadPoolExecutor(at_once) as pool:
        return _union(list(pool.map(lambda job: job(), [inheritable_thread_target(spark)(job) for job in jobs])))


def merging(spark, sf_dir: str, workloads=("w1", "w2", "w4", "w5"), seeds: int = SEEDS, eps=(0.1, 0.5)) -> DataFrame:
    """Weighted against plain averages, two levels."""
    frames = []
    for w in workloads:
        h, c, t, k = inputs(spark, sf_dir, w, levels=2)
        frames.append(_named(evaluate(spark, h, c, t, {f"{m}x{m} {how}": _topdown(k, m, how=how) for m in ("hc", "hg") for how in ("weighted", "average")}, eps, seeds), workload=w))
    return _union(frames)


def two_levels(spark, sf_dir: str, workloads=("w1", "w2", "w3", "w4", "w5"), seeds: int = SEEDS, eps=(0.1, 0.5)) -> DataFrame:
    """All four pairs of methods, two levels."""
    frames = []
    for w in workloads:
        h, c, t, k = inputs(spark, sf_dir, w, levels=2)
        frames.append(_named(evaluate(spark, h, c, t, {f"{a}x{b}": _topdown(k, [a, b]) for a in ("hc", "hg") for b in ("hc", "hg")}, eps, seeds), workload=w))
    return _union(frames)


def three_levels(spark, sf_dir: str, workloads=("w1", "w2", "w3", "w4", "w5"), seeds: int = SEEDS, eps=(0.1, 0.5)) -> DataFrame:
    """One method at all levels, in full and with the root restricted to three regions."""

    def one(w: str, nodes: list[str] | None) -> DataFrame:
        h, c, t, k = inputs(spark, sf_dir, w, nodes=nodes)
        return _named(evaluate(spark, h, c, t, {"hcxhcxhc": _topdown(k), "hgxhgxhg": _topdown(k, "hg")}, eps, seeds), workload=w, root="all" if nodes is None else "restricted")

    return _beside(spark, [lambda w=w, nodes=nodes: one(w, nodes) for w in workloads for nodes in (None, ["AMERICA", "ASIA", "EUROPE"])])


def budget_sweep(spark, sf_dir: str, workloads=("w1", "w3", "w4", "w5"), seeds: int = SEEDS, eps=GRID) -> DataFrame:
    """Error by budget of a level."""

    def one(w: str) -> DataFrame:
        h, c, t, k = inputs(spark, sf_dir, w)
        return _named(evaluate(spark, h, c, t, {"hc": _topdown(k), "hg": _topdown(k, "hg"), "bottom_up": _bottom_up(k)}, tuple(eps), seeds), workload=w)

    return _beside(spark, [lambda w=w: one(w) for w in workloads], 4)


def naive_table(spark, sf_dir: str, workload: str = "w1", seeds: int = SEEDS, ceilings=(64, 1_000, 10_000, 100_000)) -> DataFrame:
    """The naive method at the root with a budget of 1, by ceiling, and hc beside it."""
    frames = []
    for k in ceilings:
        h, c, t, _ = inputs(spark, sf_dir, workload, ceiling=k, levels=1)
        frames.append(_named(evaluate(spark, h, c, t, {"naive": lambda h, c, t, r, k=k: estimators.estimate_naive(h, c, r, k), "hc": lambda h, c, t, r, k=k: estimators.estimate_cumulative(h, c, r, k)}, (1.0,), seeds), workload=workload, ceiling=k))
    return _union(frames)


def bottom_up_table(spark, sf_dir: str, workloads=("w1", "w2", "w3", "w4", "w5"), seeds: int = SEEDS) -> DataFrame:
    """Bottom-up against top-down at a total budget of 1."""
    frames = []
    for w in workloads:
        h, c, t, k = inputs(spark, sf_dir, w)
        frames.append(_named(evaluate(spark, h, c, t, {"top_down": _topdown(k), "bottom_up": _bottom_up(k)}, (1.0 / t.levels,), seeds), workload=w))
    return _union(frames)


def many_leaves(spark, sf_dir: str, seeds: int = SEEDS) -> DataFrame:
    """The same with 125 leaves, where adding up leaves costs most at the root."""
    return bottom_up_table(spark, sf_dir, ("w9",), seeds)


def large_sizes(spark, sf_dir: str, seeds: int = SEEDS) -> DataFrame:
    """Few groups of large sizes, where sorted sizes do best."""
    h, c, t, k = inputs(spark, sf_dir, "w20")
    return _named(evaluate(spark, h, c, t, {"hc": _topdown(k), "hg": _topdown(k, "hg"), "bottom_up": _bottom_up(k)}, (1 / 3,), seeds), workload="w20")


def error_picture(spark, sf_dir: str, workloads=("w2", "w4"), seeds: int = SEEDS, eps: float = 0.1) -> DataFrame:
    """Where along the sorted groups each method errs: (workload, method, bucket, min_size, max_size, mean absolute error)."""
    frames = []
    for w in workloads:
        h, c, t, k = inputs(spark, sf_dir, w, levels=1)
        runs, _ = run_grid(spark, (eps,), seeds)
        for m in ("hc", "hg"):
            e = estimators.estimate(m, h, c, runs, k)
            p = metrics.error_profile(metrics.for_runs(h, runs), e)
            frames.append(p.groupBy("bucket").agg(F.min("min_size").alias("min_size"), F.max("max_size").alias("max_size"), F.avg(F.abs(F.col("error") / F.col("n"))).alias("mean_error")).select(F.lit(w).alias("workload"), F.lit(m).alias("method"), "*"))
    return _union(frames)


def ceilings(spark, sf_dir: str, workload: str = "w1", seeds: int = SEEDS, tried=(64, 2_000, 20_000, 100_000)) -> DataFrame:
    """hc at the root is insensitive to the ceiling: error, and the largest size released."""
    frames = []
    runs, _ = run_grid(spark, (1.0,), seeds)
    for k in tried:
        h, c, t, _k = inputs(spark, sf_dir, workload, ceiling=k, levels=1)
        e = release.frozen(estimators.estimate_cumulative(h, c, runs, k))
        err = metrics.emd(metrics.for_runs(h, runs), e).join(e.groupBy("run_id").agg(F.max("size").alias("top")), "run_id")
        frames.append(err.agg(F.avg("emd").alias("emd"), F.max("top").alias("largest_size")).select(F.lit(k).alias("ceiling"), "*"))
    return _union(frames)


def norms(spark, sf_dir: str, workloads=("w1", "w2", "w3", "w4", "w5"), seeds: int = SEEDS) -> DataFrame:
    """Absolute against squared fits at the root, budget 0.1."""
    frames = []
    for w in workloads:
        h, c, t, k = inputs(spark, sf_dir, w, levels=1)
        frames.append(_named(evaluate(spark, h, c, t, {"hc l1": lambda h, c, t, r, k=k: estimators.estimate_cumulative(h, c, r, k, 1), "hc l2": lambda h, c, t, r, k=k: estimators.estimate_cumulative(h, c, r, k, 2), "hg l1": lambda h, c, t, r: estimators.estimate_sorted(h, r, 1), "hg l2": lambda h, c, t, r: estimators.estimate_sorted(h, r, 2)}, (0.1,), seeds), workload=w))
    return _union(frames)


def tail(spark, sf_dir: str, seeds: int = SEEDS) -> DataFrame:
    """The synthetic tail with outliers up to 10,000."""
    h, c, t, k = inputs(spark, sf_dir, "w2")
    return _named(evaluate(spark, h, c, t, {"hc": _topdown(k), "hg": _topdown(k, "hg")}, (0.5,), seeds), workload="w2")


def categories(spark, sf_dir: str, seeds: int = SEEDS) -> DataFrame:
    """Six categories of disjoint entities: each run has the whole budget, as disjoint inputs compose in parallel."""
    frames = []
    for w in sorted(x for x in WORKLOADS if x.startswith("w6_")):
        h, c, t, k = inputs(spark, sf_dir, w)
        frames.append(_named(evaluate(spark, h, c, t, {"hc": _topdown(k), "hg": _topdown(k, "hg"), "bottom_up": _bottom_up(k)}, (1.0 / t.levels,), seeds), workload=w))
    return _union(frames)


def other_shapes(spark, sf_dir: str, seeds: int = SEEDS) -> DataFrame:
    """Heavy tail (by sorted sizes), time, products, and inputs without a hierarchy; all levels of each."""
    frames = []
    for w, m in (("w16", "hg"), ("w17", "hc"), ("w18", "hc"), ("w19", "hc"), ("w19b", "hc"), ("w21", "hc"), ("w21b", "hc"), ("w21c", "hc"), ("w21d", "hg")):
        h, c, t, k = inputs(spark, sf_dir, w)
        frames.append(_named(evaluate(spark, h, c, t, {m: _topdown(k, m)}, (0.5,), seeds), workload=w))
    return _union(frames)


def ratios(spark, sf_dir: str, workloads=("w1", "w2", "w4", "w5"), seeds: int = SEEDS) -> DataFrame:
    """Errors against each other, by level: weighted to plain averages, bottom-up to top-down, top-down to omniscient."""
    frames = []
    for w in workloads:
        h, c, t, k = inputs(spark, sf_dir, w)
        report = release.frozen(evaluate(spark, h, c, t, {"weighted": _topdown(k), "average": _topdown(k, how="average"), "bottom_up": _bottom_up(k)}, (1.0 / t.levels,), seeds))
        for of, to in (("average", "weighted"), ("bottom_up", "weighted"), ("weighted", "omniscient")):
            frames.append(_named(metrics.compare(report, of, to), workload=w, of=of, to=to))
    return _union(frames)


EXPERIMENTS: dict[str, Callable[..., DataFrame]] = {f.__name__: f for f in (merging, two_levels, three_levels, budget_sweep, naive_table, bottom_up_table, many_leaves, large_sizes, error_picture, ceilings, norms, tail, categories, other_shapes, ratios)}
