"""Questions to a released profile; post-processing, free of budget."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def groups_at_least(hist: DataFrame, size: int, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    return hist.groupBy(*keys).agg(F.sum(F.when(F.col("size") >= size, F.col("cnt")).otherwise(0)).alias("n"))


def quantile_sizes(hist: DataFrame, shares: list[float], keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    """Smallest size that at least the share of the node's groups do not exceed."""
    w = Window.partitionBy(*keys)
    run = hist.withColumn("upto", F.sum("cnt").over(w.orderBy("size").rowsBetween(Window.unboundedPreceding, 0))).withColumn("g", F.sum("cnt").over(w))
    return run.groupBy(*keys).agg(*[F.min(F.when(F.col("upto") >= q * F.col("g"), F.col("size"))).alias(f"q{round(100 * q)}") for q in shares])


def summary(hist: DataFrame, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    """Groups, mean size, share of groups of one, and the Gini coefficient of the sizes."""
    w = Window.partitionBy(*keys).orderBy("size").rowsBetween(Window.unboundedPreceding, 0)
    run = hist.where("cnt > 0").withColumn("below", F.sum("cnt").over(w) - F.col("cnt"))
    rank_sum = F.col("cnt") * F.col("below") + F.col("cnt") * (F.col("cnt") + 1) / 2
    a = run.groupBy(*keys).agg(F.sum("cnt").alias("g"), F.sum(F.col("cnt") * F.col("size")).alias("e"), F.sum(F.when(F.col("size") == 1, F.col("cnt")).otherwise(0)).alias("ones"), F.sum(F.col("size") * rank_sum).alias("ranked"))
    gini = F.try_divide(2 * F.col("ranked"), F.col("g") * F.col("e")) - F.try_divide(F.col("g") + 1, F.col("g"))
    return a.select(*keys, F.col("g").alias("n_groups"), F.round(F.try_divide("e", "g"), 6).alias("mean_size"), F.round(F.try_divide("ones", "g"), 6).alias("share_of_ones"), F.round(gini, 6).alias("gini"))


def largest_groups(hist: DataFrame, k: int, keys: tuple[str, ...] = ("level", "node_id")) -> DataFrame:
    """The k largest group sizes of each node as (keys, size, n)."""
    w = Window.partitionBy(*keys).orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, 0)
    run = hist.where("cnt > 0").withColumn("upto", F.sum("cnt").over(w))
    return run.where(F.col("upto") - F.col("cnt") < k).select(*keys, "size", F.least(F.col("cnt"), k - (F.col("upto") - F.col("cnt"))).alias("n"))
