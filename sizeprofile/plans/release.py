"""Whole releases: top-down consistency and the baselines."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.budget import BudgetLedger
from ..functions.noise import SecretSeed, laplace_noise
from ..operators import estimators, matching, profile
from ..operators.estimators import KEYS
from ..operators.tree import RegionTree
from ..sources.storage import frozen


def merge(match: DataFrame, how: str = "weighted") -> DataFrame:
    """The two sizes of each matched pair fused: inverse-variance weighted or plain average, rounded half up."""
    p, c, vp, vc = (F.col(x).cast("double") for x in ("p_new", "c_size", "p_var", "c_var"))
    if how == "weighted":
        size: Column = (p / vp + c / vc) / (F.lit(1.0) / vp + F.lit(1.0) / vc)
        var: Column = F.lit(1.0) / (F.lit(1.0) / vp + F.lit(1.0) / vc)
    elif how == "average":
        size, var = (p + c) / F.lit(2.0), (vp + vc) / F.lit(4.0)
    else:
        raise ValueError(f"unknown merge {how}")
    merged = match.select("run_id", F.col("child_id").alias("node_id"), F.col("c_size").alias("old"), F.floor(size + 0.5).cast("long").alias("new"), var.alias("var"), "n")
    return merged.groupBy("run_id", "node_id", "old", "new", "var").agg(F.sum("n").alias("cnt"))


def top_down(estimates: DataFrame, tree: RegionTree, how: str = "weighted", share: str = "hamilton", match_on: str = "initial", freeze: bool = True) -> DataFrame:
    """(run_id, level, node_id, size, cnt) consistent at all nodes, from estimates with variances of all levels.

    Level by level, the groups of each parent are matched with those of its children, and each child group gets the
    fused size. The leaves' results are then summed upwards, so that every parent is the sum of its children. Groups
    are matched by the first estimates of a level (`initial`) or by the fused sizes (`updated`).
    """
    if match_on not in ("initial", "updated"):
        raise ValueError(f"unknown match_on {match_on}")
    links = tree.small(tree.nodes().select("level", "node_id", "parent_id"))
    now = estimates.where("level = 0").select("run_id", "node_id", F.col("size").alias("old"), F.col("size").alias("new"), "var", "cnt")
    for level in range(1, tree.levels):
        key = "old" if match_on == "initial" else "new"
        parent = now.groupBy("run_id", F.col("node_id").alias("parent_id"), F.col(key).alias("p_size"), F.col("new").alias("p_new"), F.col("var").alias("p_var")).agg(F.sum("cnt").alias("cnt"))
        child = estimates.where(F.col("level") == level).join(links, ["level", "node_id"]).select("run_id", "parent_id", F.col("node_id").alias("child_id"), F.col("size").alias("c_size"), F.col("var").alias("c_var"), "cnt")
        now = merge(matching.match_runs(parent, child, share), how)
        if freeze and level + 1 < tree.levels:
            now = frozen(now)
    leaves = now.groupBy("run_id", F.col("node_id").alias("leaf_id"), F.col("new").alias("size")).agg(F.sum("cnt").alias("cnt"))
    return sum_up(leaves, tree)


def sum_up(leaf_hist: DataFrame, tree: RegionTree) -> DataFrame:
    """Histograms of all nodes from those of the last level's nodes."""
    return profile.rollup_histogram(leaf_hist, tree, ("run_id",)).select(*KEYS, "size", "cnt")


def release_topdown(hist: DataFrame, counts: DataFrame, tree: RegionTree, runs: DataFrame, methods: str | list[str] = "hc", ceiling: int = 100_000, how: str = "weighted", p_c: int = 1, p_g: int = 2, match_on: str = "initial", share: str = "hamilton", exact_variance: bool = False, block_source: str = "rounded", estimates: dict[str, DataFrame] | None = None) -> DataFrame:
    """The whole method. `runs` carries the budget of one level; the total is levels times that.

    Variances of sorted sizes come from runs of equal rounded sizes, or (`block_source="fit"`) of equal fits. `estimates`
    may hold, by method, frozen estimates of all levels made before with the same arguments; they are used as they are.
    """
    methods = [methods] * tree.levels if isinstance(methods, str) else list(methods)
    if len(methods) != tree.levels:
        raise ValueError("one method a level")
    if estimates is None:
        est = frozen(estimators.estimate_tree(hist, counts, runs, ceiling, methods, p_c, p_g, block_source == "fit"))
    else:
        parts = [estimates[m].where(F.col("level") == k).withColumn("method", F.lit(m)) for k, m in enumerate(methods)]
        est = parts[0]
        for part in parts[1:]:
            est = est.unionByName(part)
    return top_down(estimators.variance(est, runs, exact_variance), tree, how, share, match_on)


def publish(hist: DataFrame, counts: DataFrame, tree: RegionTree, ledger: BudgetLedger, eps: float, plan: str = "top_down", seed: SecretSeed | str | None = None, **options) -> DataFrame:
    """One release that pays from the ledger before any noise is drawn: (level, node_id, size, cnt).

    `top_down` enters eps / levels for each level, `bottom_up` and `independent` likewise what they use; nodes of a level hold
    disjoint entities and cost one entry. A ledger with too little left raises, and nothing is read. The seed is secret
    unless one is given; the result is written once, as the draw must not be repeated.
    """
    plans = {"top_down": release_topdown, "bottom_up": release_bottom_up, "independent": release_independent}
    if plan not in plans:
        raise ValueError(f"unknown plan {plan}")
    if eps <= 0 or ledger.spent + eps > ledger.total * (1 + 1e-12):
        ledger.spend(plan, eps)  # raises
    levels = [tree.levels - 1] if plan == "bottom_up" else range(tree.levels)
    for level in levels:
        ledger.spend(f"{plan} {len(ledger.entries)}: level {level}", eps / len(levels))
    seed = SecretSeed() if seed is None else seed
    runs = estimators.runs_table(hist.sparkSession, [(0, str(seed), eps / len(levels))])
    return frozen(plans[plan](hist, counts, tree, runs, **options).drop("run_id"))


def private_ceiling(sizes: DataFrame, ledger: BudgetLedger, eps: float = 1e-4, seed: SecretSeed | str | None = None) -> int:
    """A private ceiling that pays from the ledger."""
    ledger.spend(f"ceiling {len(ledger.entries)}", eps)
    seed = SecretSeed() if seed is None else seed
    return max(1, estimators.estimate_ceiling(sizes, str(seed), eps).first().ceiling)


def release_bottom_up(hist: DataFrame, counts: DataFrame, tree: RegionTree, runs: DataFrame, method: str = "hc", ceiling: int = 100_000, p_c: int = 1) -> DataFrame:
    """Baseline: the whole budget (`runs`.eps is here the total) at the leaves, sums above."""
    last = tree.levels - 1
    est = frozen(profile.gathered(estimators.estimate(method, hist.where(F.col("level") == last), counts.where(F.col("level") == last), runs, ceiling, p_c)))
    return sum_up(est.select("run_id", F.col("node_id").alias("leaf_id"), "size", "cnt"), tree)


def release_independent(hist: DataFrame, counts: DataFrame, tree: RegionTree, runs: DataFrame, methods: str | list[str] = "hc", ceiling: int = 100_000) -> DataFrame:
    """Baseline: every node by itself; parents are in general not the sums of their children."""
    methods = [methods] * tree.levels if isinstance(methods, str) else list(methods)
    return estimators.estimate_tree(hist, counts, runs, ceiling, methods).select(*KEYS, "size", "cnt")


def release_mean_consistency(estimates: DataFrame, tree: RegionTree) -> DataFrame:
    """Baseline: least squares over the tree, cell by cell, with equal variances. Sums hold, but cells may be negative
    or fractional. Upwards each node combines its own cell with the sum of its children by inverse variances; downwards
    what is left over goes to the children in proportion to their variances.
    """
    nodes = tree.nodes()
    sizes = estimates.select("run_id", "size").distinct()
    grid = sizes.crossJoin(tree.small(nodes)).join(estimates, [*KEYS, "size"], "left").select(*KEYS, "parent_id", "size", F.coalesce("cnt", F.lit(0)).cast("double").alias("y"))
    at = lambda level: grid.where(F.col("level") == level)
    last = tree.levels - 1
    up = {last: at(last).select("run_id", "node_id", "parent_id", "size", F.col("y").alias("z"), F.lit(1.0).alias("v"))}
    for level in range(last - 1, -1, -1):
        below = up[level + 1].groupBy("run_id", F.col("parent_id").alias("node_id"), "size").agg(F.sum("z").alias("s"), F.sum("v").alias("sv"))
        up[level] = at(level).join(below, ["run_id", "node_id", "size"]).select("run_id", "node_id", "parent_id", "size", ((F.col("y") + F.col("s") / F.col("sv")) / (1 + 1 / F.col("sv"))).alias("z"), (1 / (1 + 1 / F.col("sv"))).alias("v"))
    done = up[0].select("run_id", "node_id", "size", F.col("z").alias("h"))
    out = done.select("run_id", F.lit(0).alias("level"), "node_id", "size", F.col("h").alias("cnt"))
    for level in range(1, tree.levels):
        below = up[level].groupBy("run_id", F.col("parent_id").alias("pid"), "size").agg(F.sum("z").alias("s"), F.sum("v").alias("sv"))
        parent = done.select("run_id", F.col("node_id").alias("pid"), "size", F.col("h").alias("ph")).join(below, ["run_id", "pid", "size"])
        done = up[level].join(parent, (up[level].run_id == parent.run_id) & (up[level].parent_id == parent.pid) & (up[level].size == parent.size)).select(up[level].run_id, "node_id", up[level].size, (F.col("z") + (F.col("ph") - F.col("s")) * F.col("v") / F.col("sv")).alias("h"))
        out = out.unionByName(done.select("run_id", F.lit(level).alias("level"), "node_id", "size", F.col("h").alias("cnt")))
    return out


_CURVE = "slope array<double>, total array<double>, inner array<double>"


def _summed_curves(curves: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """The sum of piecewise linear functions that begin at 0, each given by its break points and ending with slope 1/2 a leaf below it."""
    at = np.unique(np.concatenate([x for x, _ in curves]))
    total = np.zeros(len(at))
    for x, y in curves:
        end = (y[-1] - y[-2]) / (x[-1] - x[-2])
        total += np.where(at > x[-1], y[-1] + (at - x[-1]) * end, np.interp(at, x, y))
    return at, total


def nonnegative_least_squares(noisy: DataFrame, tree: RegionTree) -> DataFrame:
    """(level, node_id, x): the non-negative leaf totals, and their sums above, nearest in squares to noisy values `y` of all nodes.

    Exact. A subtree's best total is a non-decreasing piecewise linear function of the marginal cost of one more group
    there; a leaf's is max(0, y + slope / 2). The functions of siblings add up, and the parent's own term shears the sum. Upwards
    one pass a level builds them, at the root the marginal cost is 0, and downwards each child reads its total off
    its own function. A function has at most a break point a leaf below; its numbers are all that is shuffled.
    """
    last = tree.levels - 1
    nodes = noisy.select("level", "node_id", "y").join(tree.nodes(), ["level", "node_id"])

    def leaf(y: float) -> tuple[list, list, list]:
        zero = -2 * y  # below this slope the leaf is empty
        return [zero, zero + 2], [0.0, 1.0], [zero, zero + 2]

    def start(batches):
        for pdf in batches:
            got = [leaf(y) for y in pdf["y"]]
            yield pdf.assign(slope=[g[0] for g in got], total=[g[1] for g in got], inner=[g[2] for g in got])

    def combine(key, own: pd.DataFrame, kids: pd.DataFrame) -> pd.DataFrame:
        at, total = _summed_curves([(np.asarray(s), np.asarray(t)) for s, t in zip(kids["slope"], kids["total"])])
        at, total = np.r_[at, at[-1] + 2], np.r_[total, total[-1] + len_slope(kids) * 2]
        out = own[["level", "node_id", "parent_id"]].copy()
        out["slope"], out["total"], out["inner"] = [(at + 2 * (total - own["y"].iloc[0])).tolist()], [total.tolist()], [at.tolist()]
        return out

    def len_slope(kids: pd.DataFrame) -> float:
        return sum((t[-1] - t[-2]) / (s[-1] - s[-2]) for s, t in zip(kids["slope"], kids["total"]))

    shape = f"level int, node_id string, parent_id string, {_CURVE}"
    curves = {last: frozen(nodes.where(F.col("level") == last).select("level", "node_id", "parent_id", "y").mapInPandas(start, f"level int, node_id string, parent_id string, y double, {_CURVE}").drop("y"))}
    for level in range(last - 1, -1, -1):
        own = nodes.where(F.col("level") == level).select("level", "node_id", "parent_id", "y")
        curves[level] = frozen(own.groupBy("node_id").cogroup(curves[level + 1].groupBy("parent_id")).applyInPandas(combine, shape))

    def read(batches):
        for pdf in batches:
            x, inner = [], []
            for goal, slope, total, below in zip(pdf["goal"], pdf["slope"], pdf["total"], pdf["inner"]):
                slope, total, below = np.asarray(slope), np.asarray(total), np.asarray(below)
                if goal > slope[-1]:  # beyond the last break point
                    k = (goal - slope[-1]) / (slope[-1] - slope[-2])
                    x.append(total[-1] + k * (total[-1] - total[-2]))
                    inner.append(below[-1] + k * (below[-1] - below[-2]))
                elif goal < slope[0]:  # empty: so is all below
                    x.append(0.0)
                    inner.append(min(below[0], goal))
                else:
                    x.append(float(np.interp(goal, slope, total)))
                    inner.append(float(np.interp(goal, slope, below)))
            yield pdf[["level", "node_id"]].assign(x=x, inner=inner)

    out, goals = None, None
    for level in range(tree.levels):
        asked = curves[level].withColumn("goal", F.lit(0.0)) if goals is None else curves[level].join(goals, "parent_id")
        now = frozen(asked.select("level", "node_id", "goal", "slope", "total", "inner").mapInPandas(read, "level int, node_id string, x double, inner double"))
        goals = now.select(F.col("node_id").alias("parent_id"), F.col("inner").alias("goal"))
        out = now.drop("inner") if out is None else out.unionByName(now.drop("inner"))
    return out


def private_group_counts(counts: DataFrame, tree: RegionTree, seed: str, eps: float, ledger: BudgetLedger | None = None) -> DataFrame:
    """Extension for private groups: noisy counts of groups of all nodes, made non-negative whole numbers that add up.

    eps is split evenly over levels (a group touches one node of each), and entered in the ledger if one is given. The noisy
    counts are fitted by non-negative least squares over the tree; then, from the root down, each node's children are
    rounded by largest remainders to their parent's whole number.
    """
    if ledger:
        ledger.spend(f"group counts {len(ledger.entries)}", eps)
    scale = tree.levels / eps
    noisy = counts.select("level", "node_id", (F.col("g") + laplace_noise(scale, seed, F.col("level"), F.col("node_id"), F.lit("groups"))).cast("double").alias("y"))
    fit = nonnegative_least_squares(frozen(noisy), tree)
    nodes = tree.nodes()
    now = fit.where("level = 0").select("node_id", F.floor(F.col("x") + 0.5).cast("long").alias("g"))
    out = now.select(F.lit(0).alias("level"), "node_id", "g")
    for level in range(1, tree.levels):
        kids = fit.where(F.col("level") == level).join(nodes.where(F.col("level") == level).select("node_id", "parent_id"), "node_id")
        cells = kids.join(now.select(F.col("node_id").alias("parent_id"), "g"), "parent_id").select("parent_id", F.col("node_id").alias("size"), F.col("x").alias("projected"), "g")
        now = frozen(estimators.round_largest_remainder(cells, keys=("parent_id",)).select(F.col("size").alias("node_id"), F.col("cnt").alias("g")))
        out = out.unionByName(now.select(F.lit(level).alias("level"), "node_id", "g"))
    return out


def best_methods(hist: DataFrame, counts: DataFrame, tree: RegionTree, runs: DataFrame, ceiling: int) -> list[str]:
    """The method with the smaller error at each level, chosen by the truth. Not private: an ablation yardstick only."""
    from ..operators import metrics

    truth, best = metrics.for_runs(hist, runs), {}
    for m in ("hc", "hg"):
        report = metrics.run_report(metrics.level_report(metrics.emd(truth, estimators.estimate(m, hist, counts, runs, ceiling)), counts))
        for r in report.collect():  # one row a level
            best[r.level] = min(best.get(r.level, (float("inf"), "")), (r.emd, m))
    return [best[k][1] for k in range(tree.levels)]
