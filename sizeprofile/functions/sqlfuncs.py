"""SQL functions and views for users of Spark SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from . import aggregates
from .isotonic import isotonic

_FUNCTIONS = (
    "create or replace temporary function sp_uniform(k string) returns double return (cast(conv(substring(md5(k), 1, 13), 16, 10) as bigint) + 0.5) / 4503599627370496.0D",
    "create or replace temporary function sp_geometric(u double, scale double) returns double return floor(ln(u) / (-1.0D / scale))",
    "create or replace temporary function sp_inverse_variance(s1 double, v1 double, s2 double, v2 double) returns double return (s1 / v1 + s2 / v2) / (1.0D / v1 + 1.0D / v2)",
)


@udtf(returnType="node_id string, idx bigint, fit double")
class IsotonicFit:
    """sp_isotonic(p, TABLE(t) PARTITION BY node_id ORDER BY idx): the fit of column `value` in each partition."""

    def __init__(self):
        self.rows, self.p = [], 2

    def eval(self, p: int, row):
        self.rows.append((row["node_id"], row["idx"], row["value"]))
        self.p = p

    def terminate(self):
        for (node, idx, _), fit in zip(self.rows, isotonic([r[2] for r in self.rows], self.p)):
            yield node, idx, float(fit)


def register(spark: SparkSession, released: dict[str, DataFrame] | None = None, truth: dict[str, DataFrame] | None = None, allow_truth: bool = False) -> None:
    """SQL functions, the table function, and views sp_<name>; views over the truth only if asked for, as sp_true_<name>."""
    for sql in _FUNCTIONS:
        spark.sql(sql)
    spark.udtf.register("sp_isotonic", IsotonicFit)
    aggregates.register(spark)
    for name, df in (released or {}).items():
        df.createOrReplaceTempView(f"sp_{name}")
    if truth and not allow_truth:
        raise PermissionError("views over the truth need allow_truth=True")
    for name, df in (truth or {}).items():
        df.createOrReplaceTempView(f"sp_true_{name}")
