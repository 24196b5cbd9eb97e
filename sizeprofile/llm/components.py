"""Connected components by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written


def _flat(links: DataFrame) -> bool:
    """Whether the links are stars: each node that points down points to one node, which points to none."""
    ends = links.select(F.col("a").alias("x"), F.lit(1).alias("out"), F.lit(0).alias("into")).unionByName(links.select(F.col("b").alias("x"), F.lit(0).alias("out"), F.lit(1).alias("into")))
    return ends.groupBy("x").agg(F.sum("out").alias("out"), F.sum("into").alias("into")).where("out > 1 or (out = 1 and into > 0)").isEmpty()


def connected_components(edges: DataFrame) -> DataFrame:
    """node and root (the smallest node of its component) of every node of the links (a, b); self-links are ignored.

    Each step hangs neighbours under the smallest node seen, which shortens paths as fast as they can double, until
    all links point to a root. Smallest neighbours are partial aggregates, written before the step back: the join then
    has two plain sides, so AQE can split the links of a node that has very many. Every step is a written table.
    """
    now = written(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    while not _flat(now):
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = written(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("root")), "least")
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("root").alias("b"))
        large = written(large.where("a <> b").distinct(), "large-star")
        least = written(large.groupBy("a").agg(F.min("b").alias("root")), "least")
        small = large.join(least, "a").select(F.col("b").alias("a"), F.col("root").alias("b")).unionByName(least.select("a", F.col("root").alias("b")))
        now = written(small.where("a <> b").distinct(), "small-star")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
