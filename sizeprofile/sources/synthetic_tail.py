"""A synthetic tail for truncated sizes, and outliers, per level-1 region."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.noise import keyed_uniform


def extend_tail(sizes: DataFrame, region_of: DataFrame, seed: str, cut: int = 7, outliers: int = 50, largest: int = 10_000) -> DataFrame:
    """(group_id, leaf_id, size): groups up to `cut`, a tail above it, and uniform outliers in 1 .. largest.

    In each region the ratio of its groups of size `cut` to those of size `cut` - 1 is the chance to survive to the
    next size. Each group at the cut goes on by a geometric draw, and adds one tail group for each size it survives to: the counts by
    size are then exactly the chain of binomials. Every new group draws a leaf of its region by itself, in
    proportion to the leaves' groups. A region whose ratio is one or more has no finite tail: an error.
    """
    base = sizes.where(F.col("size") <= cut).join(region_of, "leaf_id")
    per_leaf = base.groupBy("region", "leaf_id").agg(F.count(F.lit(1)).alias("n"))
    upto = Window.partitionBy("region").orderBy("leaf_id")
    leaves = per_leaf.select("region", "leaf_id", (F.sum("n").over(upto) - F.col("n")).alias("lo"), F.sum("n").over(upto).alias("hi"))
    counts = base.groupBy("region").agg(F.count_if(F.col("size") == cut).alias("n1"), F.count_if(F.col("size") == cut - 1).alias("n0"), F.count(F.lit(1)).alias("total"))
    rho = F.when(F.col("n1") < F.greatest("n0", F.lit(1)), F.col("n1") / F.greatest(F.col("n0"), F.lit(1))).when(F.col("n1") > 0, F.raise_error(F.concat(F.lit("no finite tail in "), F.col("region"))).cast("double")).otherwise(0.0)
    regions = counts.select("region", "total", rho.alias("rho"))
    seeds = base.where(F.col("size") == cut).join(regions, "region").where("rho > 0")
    steps = F.floor(F.ln(keyed_uniform(seed, F.col("group_id"), "tail")) / F.ln("rho")).cast("int")
    tail = seeds.withColumn("j", steps).where("j >= 1").select("region", "total", F.col("group_id").cast("string").alias("of"), F.explode(F.expr("sequence(1, j)")).alias("k"))
    tail = tail.select("region", "total", F.concat(F.lit("t"), F.col("of"), F.lit(":"), F.col("k")).alias("group_id"), (F.col("k") + cut).cast("long").alias("size"))
    far = regions.select("region", "total", F.explode(F.sequence(F.lit(1), F.lit(outliers))).alias("k"))
    size = (F.floor(keyed_uniform(seed, F.col("region"), F.col("k"), "size") * largest) + 1).cast("long")
    far = far.select("region", "total", F.concat(F.lit("o"), F.col("region"), F.lit(":"), F.col("k")).alias("group_id"), size.alias("size"))
    drawn = tail.unionByName(far).withColumn("place", F.floor(keyed_uniform(seed, F.col("group_id"), "leaf") * F.col("total")).cast("long"))
    placed = drawn.join(leaves, (drawn.region == leaves.region) & (drawn.place >= leaves.lo) & (drawn.place < leaves.hi))
    return base.select(F.col("group_id").cast("string").alias("group_id"), "leaf_id", "size").unionByName(placed.select("group_id", "leaf_id", "size"))
