"""Forms of a size profile: group sizes, histograms, cumulative, runs, sorted sizes, arrays."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .tree import RegionTree

#: Rows that one row of counts makes in a task before the next block of them may go to another.
BLOCK_ROWS = 1 << 16


def group_sizes(entities: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, leaf_id, size) of every public group; a group without entities has size 0.

    Entities are counted by group before the join, so only one partial row a group and task is shuffled. Further columns of
    the groups stay.
    """
    counts = entities.groupBy("group_id").agg(F.count(F.lit(1)).alias("n"))
    return groups.join(counts, "group_id", "left").select(*groups.columns, F.coalesce("n", F.lit(0)).cast("long").alias("size"))


def clamp_sizes(sizes: DataFrame, ceiling: int) -> DataFrame:
    return sizes.withColumn("size", F.least(F.col("size"), F.lit(ceiling).cast("long")))


def leaf_histogram(sizes: DataFrame) -> DataFrame:
    return sizes.groupBy("leaf_id", "size").agg(F.count(F.lit(1)).alias("cnt"))


def rollup_histogram(leaf_hist: DataFrame, tree: RegionTree, keys: tuple[str, ...] = ()) -> DataFrame:
    """(keys, level, node_id, size, cnt) of all nodes: leaves are scanned once and summed along their ancestors."""
    return leaf_hist.join(tree.small(tree.long()), "leaf_id").groupBy(*keys, "level", "node_id", "size").agg(F.sum("cnt").alias("cnt"))


def grouping_sets_histogram(leaf_hist: DataFrame, tree: RegionTree) -> DataFrame:
    """The same by grouping sets over the wide tree."""
    wide = leaf_hist.join(tree.small(tree.wide), "leaf_id")
    names = [f"level_{k}" for k in range(tree.levels)]
    sets = ", ".join(f"({', '.join([*names[: k + 1], 'size'])})" for k in range(tree.levels))
    level = " ".join(f"when grouping(level_{k}) = 0 then {k}" for k in range(tree.levels - 1, -1, -1))
    out = leaf_hist.sparkSession.sql(f"select {', '.join(names)}, size, sum(cnt) as cnt, case {level} end as level from {{wide}} group by grouping sets ({sets})", wide=wide)
    return out.select("level", F.coalesce(*names[::-1]).alias("node_id"), "size", "cnt")


def group_counts(hist: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    return hist.groupBy(*keys).agg(F.sum("cnt").alias("g"))


def public_counts(groups: DataFrame, tree: RegionTree) -> DataFrame:
    """(level, node_id, g) of every node of the tree from the public groups; nodes without groups have 0."""
    return summed_counts(groups.groupBy("leaf_id").agg(F.count(F.lit(1)).alias("n")), tree)


def summed_counts(leaves: DataFrame, tree: RegionTree) -> DataFrame:
    """The same from the leaves' numbers of groups (leaf_id, n)."""
    return tree.small(tree.long()).join(leaves, "leaf_id", "left").groupBy("level", "node_id").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("g"))


def to_cumulative(hist: DataFrame, nodes: DataFrame, ceiling: int, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    """(keys, size, cum) for sizes 0 .. ceiling of every node given; sizes above the ceiling count at it."""
    grid = nodes.select(*keys, F.explode(F.sequence(F.lit(0).cast("long"), F.lit(ceiling).cast("long"))).alias("size"), F.lit(0).cast("long").alias("cnt"))
    cells = grid.unionByName(clamp_sizes(hist.select(*keys, "size", "cnt"), ceiling)).groupBy(*keys, "size").agg(F.sum("cnt").alias("cnt"))
    w = Window.partitionBy(*keys).orderBy("size").rowsBetween(Window.unboundedPreceding, 0)
    return cells.select(*keys, "size", F.sum("cnt").over(w).alias("cum"))


def from_cumulative(cum: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy("size")
    return cum.select(*keys, "size", (F.col("cum") - F.lag("cum", 1, 0).over(w)).cast("long").alias("cnt")).where("cnt <> 0")


def to_runs(hist: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    """Equal sizes of a node as one run with its half-open interval of ranks (from 0)."""
    w = Window.partitionBy(*keys).orderBy("size").rowsBetween(Window.unboundedPreceding, 0)
    return hist.where("cnt > 0").select(*keys, "size", "cnt", (F.sum("cnt").over(w) - F.col("cnt")).alias("rank_lo"), F.sum("cnt").over(w).alias("rank_hi"))


def dealt(df: DataFrame, *keys: str) -> DataFrame:
    """Rows dealt by the keys over all cores, for kernels that take long over few bytes.

    A number is given, as adaptive execution else goes by bytes and puts the rows of a whole sweep into one task.
    """
    return df.repartition(df.sparkSession.sparkContext.defaultParallelism, *keys)


def gathered(df: DataFrame) -> DataFrame:
    """What such kernels return as few rows, in one part or two; adaptive execution cuts them where they are large.

    Each part that is written is a task of every later read, which opens a file for each partition it shuffles to.
    """
    return df.hint("rebalance", 2)


def exploded(counted: DataFrame, name: str, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """A row for each of `cnt` consecutive numbers from `first` on, as column `name`, with the number of its `block`.

    In two steps: blocks are dealt over all tasks before their places are made, so that neither an array nor a task
    grows with the largest count. A block stays in one partition, in ascending order.
    """
    kept = [c for c in counted.columns if c not in ("first", "cnt")]
    blocks = counted.select(*kept, "first", "cnt", F.explode(F.expr(f"sequence(0L, (cnt - 1) div {block_rows})")).alias("block"))
    dealt = blocks.repartition(int(counted.sparkSession.conf.get("spark.sql.shuffle.partitions")), *kept, "block")
    places = F.expr(f"sequence(first + block * {block_rows}, first + least(cnt, (block + 1) * {block_rows}) - 1)")
    return dealt.select(*kept, "block", F.explode(places).alias(name))


def to_sorted_sizes(hist: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    """One row a group: (keys, idx, size), ranks from the runs, without sorting the groups."""
    return exploded(to_runs(hist, keys).select(*keys, "size", F.col("rank_lo").alias("first"), "cnt"), "idx").select(*keys, "idx", "size")


def from_sorted_sizes(df: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    return df.groupBy(*keys, "size").agg(F.count(F.lit(1)).alias("cnt"))


def cumulative_to_runs(cum: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    return to_runs(from_cumulative(cum, keys), keys)


def as_array(hist: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    """One row a node with the dense array h, h[i] being the number of groups of size i."""
    filled = hist.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("size", "cnt"))).alias("m"), F.max("size").alias("top"))
    return filled.select(*keys, F.expr("transform(sequence(0L, top), i -> coalesce(m[i], 0L))").alias("h"))


def as_map(hist: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    return hist.groupBy(*keys).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("size", "cnt")))).alias("h"))


def from_array(arrays: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    return arrays.select(*keys, F.posexplode("h").alias("size", "cnt")).select(*keys, F.col("size").cast("long"), "cnt").where("cnt <> 0")


def array_cumulative(arrays: DataFrame) -> DataFrame:
    """Running sums of h as an array, by a fold (for small ceilings)."""
    return arrays.withColumn("hc", F.expr("aggregate(h, cast(array() as array<bigint>), (a, x) -> concat(a, array(coalesce(try_element_at(a, -1), 0L) + x)))"))


def dataset_stats(hist_root: DataFrame) -> DataFrame:
    """Groups, entities and distinct sizes (not private)."""
    return hist_root.agg(F.sum("cnt").alias("n_groups"), F.sum(F.col("cnt") * F.col("size")).alias("n_entities"), F.countDistinct(F.when(F.col("cnt") > 0, F.col("size"))).alias("n_sizes"), F.max("size").alias("max_size"))
