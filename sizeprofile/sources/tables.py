"""Readers of the given tables; columns are picked at the scan."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_external(spark: SparkSession, path: str, kind: str, schema: str, **options) -> DataFrame:
    """csv, json or orc with a declared schema; schemas are never inferred from data."""
    return spark.read.format(kind).schema(schema).options(**options).load(path)


def write_release(hist: DataFrame, path: str, kind: str = "parquet") -> None:
    """A released profile, partitioned by level."""
    hist.write.mode("overwrite").partitionBy("level").format(kind).save(path)
