"""Optimal matching of parent groups to child groups in run-length form, and its baselines.

Sorted pairing is optimal for absolute size gaps. Both sides of a parent are cut into rank intervals (runs of equal
sizes); overlaying the cut points gives segments in which one parent run meets one pooled child size. Cost follows the
number of distinct sizes, not the number of groups.
"""

from __future__ import annotations

import heapq
from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PARENT = ("run_id", "parent_id")
_MATCH = "run_id int, parent_id string, p_size long, p_new long, p_var double, child_id string, c_size long, c_var double, n long"
_COLUMNS = ["run_id", "parent_id", "p_size", "p_new", "p_var", "child_id", "c_size", "c_var", "n"]


def _intervals(df: DataFrame, order: list[str]) -> DataFrame:
    w = Window.partitionBy(*PARENT).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumn("hi", F.sum("cnt").over(w)).withColumn("lo", F.col("hi") - F.col("cnt"))


def segments(parent_runs: DataFrame, child_runs: DataFrame) -> DataFrame:
    """(run_id, parent_id, lo, n, p_size, p_new, p_var, c_size).

    parent_runs: (run_id, parent_id, p_size, p_new, p_var, cnt), matched in the order of p_size, p_new, p_var;
    child_runs: (run_id, parent_id, child_id, c_size, c_var, cnt). Both must count the same groups for each parent.
    """
    top = _intervals(parent_runs.where("cnt > 0"), ["p_size", "p_new", "p_var"])
    pooled = _intervals(child_runs.where("cnt > 0").groupBy(*PARENT, "c_size").agg(F.sum("cnt").alias("cnt")), ["c_size"])
    p = F.struct("p_size", "p_new", "p_var")
    cuts = top.select(*PARENT, "lo", "hi", p.alias("p"), F.lit(None).cast("long").alias("c_size")).unionByName(pooled.select(*PARENT, "lo", "hi", F.lit(None).cast("struct<p_size:bigint,p_new:bigint,p_var:double>").alias("p"), "c_size"))
    points = cuts.groupBy(*PARENT, "lo").agg(F.first("p", ignorenulls=True).alias("p"), F.first("c_size", ignorenulls=True).alias("c_size"), F.max("hi").alias("hi"))
    w = Window.partitionBy(*PARENT).orderBy("lo")
    total = F.max("hi").over(Window.partitionBy(*PARENT))
    out = points.select(*PARENT, "lo", (F.lead("lo").over(w) - F.col("lo")).alias("n"), (total - F.col("lo")).alias("rest"), F.last("p", ignorenulls=True).over(w).alias("p"), F.last("c_size", ignorenulls=True).over(w).alias("c_size"))
    return out.select(*PARENT, "lo", F.coalesce("n", "rest").alias("n"), "p.*", "c_size")


def hamilton_shares(n: list[int], remaining: list[int]) -> list[list[int]]:
    """Segments one after another, each shared in proportion to what the children have left: floors, then one more for
    the largest remainders (ties: the earlier child). The last segment takes what is left."""
    left, out = list(remaining), []
    for take in n:
        total = sum(left)
        share = [take * r // total for r in left] if total else [0] * len(left)
        short = take - sum(share)
        for k in sorted(range(len(left)), key=lambda k: (-(take * left[k] % total) if total else 0, k))[:short]:
            share[k] += 1
        left = [a - b for a, b in zip(left, share)]
        out.append(share)
    return out


def spread_shares(n: list[int], counts: list[int]) -> list[list[int]]:
    """Item j of a child with c items stands at (j - 1/2) / c; segments take the items in that order (ties: child).

    A prefix of any length is nearly proportional, and no state passes from segment to segment. Found by bisection.
    """
    total, done, out, at = sum(counts), [0] * len(counts), [], 0
    for take in n:
        at += take
        x = at / total if total else 0.0
        now = [max(d, min(c, int(np.floor(c * x + 0.5)) - 1)) for c, d in zip(counts, done)]
        while sum(now) > at:  # too far on some: step back the latest
            k = max((k for k in range(len(now)) if now[k] > done[k]), key=lambda k: (Fraction(2 * now[k] - 1, 2 * counts[k]), k))
            now[k] -= 1
        heap = [(Fraction(2 * a + 1, 2 * c), k) for k, (a, c) in enumerate(zip(now, counts)) if a < c]
        heapq.heapify(heap)
        for _ in range(at - sum(now)):
            _, k = heapq.heappop(heap)
            now[k] += 1
            if now[k] < counts[k]:
                heapq.heappush(heap, (Fraction(2 * now[k] + 1, 2 * counts[k]), k))
        out.append([a - b for a, b in zip(now, done)])
        done = now
    return out


def apportion(segs: DataFrame, child_runs: DataFrame, method: str = "hamilton") -> DataFrame:
    """Share each segment among the children that hold its size: the matching, with multiplicities `n`.

    Runs of different child sizes are separate groups, so a large parent is spread over as many tasks as it has sizes.
    A task reads its groups one after another from sorted rows, first the children and then the segments of each.
    """
    shares = {"hamilton": hamilton_shares, "spread": spread_shares}[method]
    keys = [*PARENT, "c_size"]
    zero = F.lit(0).cast("long")
    kids = child_runs.where("cnt > 0").select(*keys, F.lit(0).alias("kind"), F.col("child_id").alias("name"), zero.alias("lo"), F.col("cnt").alias("n"), F.col("c_var").alias("var"), zero.alias("p_size"), zero.alias("p_new"))
    cuts = segs.select(*keys, F.lit(1).alias("kind"), F.lit("").alias("name"), "lo", "n", F.col("p_var").alias("var"), "p_size", "p_new")
    rows = kids.unionByName(cuts).repartition(*keys).sortWithinPartitions(*keys, "kind", "name", "lo")

    def share(batches):
        key, children, parts, out = None, [], [], []

        def deal():
            for s, split in zip(parts, shares([s[6] for s in parts], [c[6] for c in children])):
                out.extend((key[0], key[1], s[8], s[9], s[7], c[4], key[2], c[7], n) for c, n in zip(children, split) if n)

        for pdf in batches:
            for r in pdf.itertuples(index=False, name=None):
                if r[:3] != key:
                    deal()
                    key, children, parts = r[:3], [], []
                (parts if r[3] else children).append(r)
            if out:
                yield pd.DataFrame(out, columns=_COLUMNS)
                out = []
        deal()
        if out:
            yield pd.DataFrame(out, columns=_COLUMNS)

    return rows.mapInPandas(share, _MATCH)


def match_runs(parent_runs: DataFrame, child_runs: DataFrame, method: str = "hamilton") -> DataFrame:
    return apportion(segments(parent_runs, child_runs), child_runs, method)


def matching_cost(match: DataFrame) -> DataFrame:
    return match.groupBy(*PARENT).agg(F.sum(F.col("n") * F.abs(F.col("p_size") - F.col("c_size"))).alias("cost"))


def check_matching(match: DataFrame, parent_runs: DataFrame, child_runs: DataFrame) -> DataFrame:
    """(check, bad): rows of the marginals that differ from the runs. Both must be 0."""
    sides = []
    for name, runs, keys in (("parent", parent_runs, [*PARENT, "p_size", "p_new", "p_var"]), ("child", child_runs, [*PARENT, "child_id", "c_size", "c_var"])):
        both = match.groupBy(*keys).agg(F.sum("n").alias("n")).unionByName(runs.where("cnt > 0").groupBy(*keys).agg((-F.sum("cnt")).alias("n")))
        sides.append(both.groupBy(*keys).agg(F.sum("n").alias("n")).agg(F.count_if(F.col("n") != 0).alias("bad")).select(F.lit(name).alias("check"), "bad"))
    return sides[0].unionByName(sides[1])


def greedy_edge_cost(parent: list[int], child: list[int]) -> int:
    """Baseline: take edges by increasing gap while both ends are free. Quadratic; small inputs only."""
    used_p, used_c, cost = set(), set(), 0
    for gap, i, j in sorted((abs(p - c), i, j) for i, p in enumerate(parent) for j, c in enumerate(child)):
        if i not in used_p and j not in used_c:
            used_p.add(i)
            used_c.add(j)
            cost += gap
    return cost


def match_greedy_edges(parent_sizes: DataFrame, child_sizes: DataFrame, most: int = 200) -> DataFrame:
    """The greedy baseline on (run_id, parent_id, size) rows, one per group; at most `most` groups a parent."""

    def run(keys, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if max(len(a), len(b)) > most:
            raise ValueError(f"the greedy baseline takes at most {most} groups a parent")
        return pd.DataFrame({"run_id": [keys[0]], "parent_id": [keys[1]], "cost": [greedy_edge_cost(a["size"].tolist(), b["size"].tolist())]})

    return parent_sizes.groupBy(*PARENT).cogroup(child_sizes.groupBy(*PARENT)).applyInPandas(run, "run_id int, parent_id string, cost long")


def optimal_cost(parent: list[int], child: list[int]) -> int:
    """General minimum-cost matching by shortest augmenting paths with potentials (cubic; for small inputs).

    Makes no use of the order of sizes: each new group is matched along the cheapest alternating path.
    """
    n = len(parent)
    gap = np.abs(np.subtract.outer(np.asarray(parent, dtype=np.int64), np.asarray(child, dtype=np.int64)))
    row_price, col_price = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
    owner = np.full(n, -1)  # the parent matched to each child
    for start in range(n):
        reach, came, seen = np.full(n, np.iinfo(np.int64).max // 4), np.full(n, -1), np.zeros(n, dtype=bool)
        row, col, at = start, -1, 0
        while row >= 0:
            price = at + gap[row] - row_price[row] - col_price
            better = ~seen & (price < reach)
            reach[better], came[better] = price[better], col
            open_ = np.flatnonzero(~seen)
            col = int(open_[np.argmin(reach[open_])])
            at, row = int(reach[col]), int(owner[col])
            seen[col] = True
        done = np.flatnonzero(seen & (owner >= 0))
        row_price[start] += at
        row_price[owner[done]] += at - reach[done]
        col_price[seen] -= at - reach[seen]
        while col >= 0:
            before = came[col]
            owner[col] = owner[before] if before >= 0 else start
            col = before
    return int(gap[owner, np.arange(n)].sum())


def match_general(parent_sizes: DataFrame, child_sizes: DataFrame, most: int = 60) -> DataFrame:
    """The general baseline on (run_id, parent_id, size) rows, one per group; at most `most` groups a parent."""

    def run(keys, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if max(len(a), len(b)) > most:
            raise ValueError(f"the general baseline takes at most {most} groups a parent")
        return pd.DataFrame({"run_id": [keys[0]], "parent_id": [keys[1]], "cost": [optimal_cost(a["size"].tolist(), b["size"].tolist())]})

    return parent_sizes.groupBy(*PARENT).cogroup(child_sizes.groupBy(*PARENT)).applyInPandas(run, "run_id int, parent_id string, cost long")
