"""Error measures. They read the truth: for evaluation only, not private."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .estimators import KEYS
from .matching import segments


def _gaps(truth: DataFrame, est: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """(keys, size, d): difference of the counts, estimate less truth, at every size of either."""
    both = est.select(*keys, "size", F.col("cnt").alias("d")).unionByName(truth.select(*keys, "size", (-F.col("cnt")).alias("d")))
    return both.groupBy(*keys, "size").agg(F.sum("d").alias("d"))


def for_runs(truth: DataFrame, runs: DataFrame) -> DataFrame:
    return truth.crossJoin(runs.select("run_id"))


def emd(truth: DataFrame, est: DataFrame, keys: tuple[str, ...] = KEYS) -> DataFrame:
    """(keys, emd): entities to add to or remove from groups, as the area between the cumulative counts."""
    w = Window.partitionBy(*keys).orderBy("size")
    steps = _gaps(truth, est, keys).select(*keys, F.abs(F.sum("d").over(w.rowsBetween(Window.unboundedPreceding, 0))).alias("gap"), (F.lead("size").over(w) - F.col("size")).alias("width"))
    return steps.groupBy(*keys).agg(F.coalesce(F.sum(F.col("gap") * F.col("width")), F.lit(0)).alias("emd"))


def _overlay(truth: DataFrame, est: DataFrame) -> DataFrame:
    node = F.concat_ws("|", "level", "node_id")
    a = truth.select("run_id", node.alias("parent_id"), F.col("size").alias("p_size"), F.col("size").alias("p_new"), F.lit(1.0).alias("p_var"), "cnt")
    b = est.select("run_id", node.alias("parent_id"), F.lit("x").alias("child_id"), F.col("size").alias("c_size"), F.lit(1.0).alias("c_var"), "cnt")
    out = segments(a, b)
    return out.withColumn("level", F.substring_index("parent_id", "|", 1).cast("int")).withColumn("node_id", F.expr("substring(parent_id, instr(parent_id, '|') + 1)"))


def emd_sorted(truth: DataFrame, est: DataFrame) -> DataFrame:
    """The same from the sorted sizes: the sum of the gaps of the sorted pairing."""
    return _overlay(truth, est).groupBy(*KEYS).agg(F.sum(F.col("n") * F.abs(F.col("p_size") - F.col("c_size"))).alias("emd"))


def error_profile(truth: DataFrame, est: DataFrame, bucket: int = 100) -> DataFrame:
    """Signed error along the sorted groups: (keys, bucket, n, error) by blocks of the start rank, and the mean size there."""
    return _overlay(truth, est).groupBy(*KEYS, F.floor(F.col("lo") / bucket).cast("long").alias("bucket")).agg(F.sum("n").alias("n"), F.sum(F.col("n") * (F.col("c_size") - F.col("p_size"))).alias("error"), F.min("p_size").alias("min_size"), F.max("p_size").alias("max_size"))


def cell_distances(truth: DataFrame, est: DataFrame, keys: tuple[str, ...] = KEYS) -> DataFrame:
    """Manhattan and squared distance of the histograms, which ignore how far groups move."""
    return _gaps(truth, est, keys).groupBy(*keys).agg(F.sum(F.abs("d")).alias("l1"), F.sum(F.col("d") * F.col("d")).alias("l2_squared"))


def level_report(errors: DataFrame, counts: DataFrame, runs: DataFrame | None = None) -> DataFrame:
    """Mean error a node within each level and run; nodes without groups count with 0.

    Without the table of `runs` they are those of the errors, for which the errors' whole plan is run a second time.
    """
    per_run = counts.select("level", "node_id").crossJoin(F.broadcast(errors.select("run_id").distinct() if runs is None else runs.select("run_id")))
    return per_run.join(errors, list(KEYS), "left").groupBy("run_id", "level").agg(F.avg(F.coalesce("emd", F.lit(0))).alias("mean_emd"), F.count(F.lit(1)).alias("nodes"))


def run_report(report: DataFrame, *keys: str) -> DataFrame:
    """Mean over runs, and the standard deviation of that mean."""
    return report.groupBy(*keys, "level").agg(F.avg("mean_emd").alias("emd"), (F.stddev_samp("mean_emd") / F.sqrt(F.count(F.lit(1)))).alias("std_of_mean"), F.count(F.lit(1)).alias("runs"))


def compare(report: DataFrame, of: str, to: str, *keys: str) -> DataFrame:
    """(keys, level, ratio) of two methods in a report with columns keys, method, level, emd."""
    wide = report.groupBy(*keys, "level").pivot("method", [of, to]).agg(F.first("emd"))
    return wide.select(*keys, "level", F.try_divide(F.col(f"`{of}`"), F.col(f"`{to}`")).alias("ratio"))


def omniscient_expected(hist: DataFrame, runs: DataFrame) -> DataFrame:
    """Expected error of one who knows which sizes occur: distinct sizes times sqrt(2) / epsilon."""
    sizes = hist.where("cnt > 0").groupBy("level", "node_id").agg(F.countDistinct("size").alias("sizes"))
    return sizes.crossJoin(runs).select(*KEYS, (F.col("sizes") * F.lit(2.0**0.5) / F.col("eps")).alias("emd"))


def omniscient_simulated(hist: DataFrame, runs: DataFrame) -> DataFrame:
    """The same by drawing Laplace noise on the occurring cells: absolute noise summed by node."""
    from ..functions.noise import laplace_noise

    cells = hist.where("cnt > 0").crossJoin(runs)
    noise = laplace_noise(F.lit(1.0) / F.col("eps"), F.col("seed"), F.col("level"), F.col("node_id"), F.col("size"), F.lit("omniscient"))
    return cells.groupBy(*KEYS).agg(F.sum(F.abs(noise)).alias("emd"))


def audit(est: DataFrame, counts: DataFrame, nodes: DataFrame, keys: tuple[str, ...] = ("run_id",)) -> DataFrame:
    """(check, bad) of a release: negative and fractional cells, node totals off the public counts, and parent cells
    that differ from the sum of their children. All must be 0."""
    whole = est.where(F.col("cnt") != F.floor("cnt")).agg(F.count(F.lit(1)).alias("bad")).select(F.lit("integral").alias("check"), "bad")
    negative = est.where("cnt < 0").agg(F.count(F.lit(1)).alias("bad")).select(F.lit("non_negative").alias("check"), "bad")
    runs = F.broadcast(est.select(*keys).distinct())
    sums = counts.crossJoin(runs).join(est.groupBy(*keys, "level", "node_id").agg(F.sum("cnt").alias("s")), [*keys, "level", "node_id"], "left")
    totals = sums.where(F.abs(F.coalesce("s", F.lit(0)) - F.col("g")) > 1e-6).agg(F.count(F.lit(1)).alias("bad")).select(F.lit("group_totals").alias("check"), "bad")
    up = est.join(nodes.where("parent_id is not null"), ["level", "node_id"]).select(*keys, (F.col("level") - 1).alias("level"), F.col("parent_id").alias("node_id"), "size", F.col("cnt").alias("d"))
    inner = nodes.select((F.col("level") - 1).alias("level")).where("level >= 0").distinct()
    down = est.join(F.broadcast(inner), "level", "left_semi").select(*keys, "level", "node_id", "size", (-F.col("cnt")).alias("d"))
    gaps = up.unionByName(down).groupBy(*keys, "level", "node_id", "size").agg(F.sum("d").alias("d"))
    additive = gaps.where(F.abs("d") > 1e-6).agg(F.count(F.lit(1)).alias("bad")).select(F.lit("parent_is_sum").alias("check"), "bad")
    return whole.unionByName(negative).unionByName(totals).unionByName(additive)
