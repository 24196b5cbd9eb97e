"""Intermediate tables in the folder that the driver and all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a temporary folder in local mode only."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is unset: on a cluster it must name a folder that all executors share")
        if not _LOCAL:
            _LOCAL.append("file://" + tempfile.mkdtemp(prefix="sizeprofile-"))
        root = _LOCAL[0]
    return root.rstrip("/")


def _remove(spark: SparkSession, path: str) -> None:
    try:
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # noqa: BLE001  at exit the gateway may be gone; the folder is temporary
        pass


def frozen(df: DataFrame) -> DataFrame:
    """Evaluate once, write, and read back: noise is drawn once, and lost executors cost no recomputation.

    A second evaluation of keyed noise gives the same draws, but a release must not depend on that. The table is
    removed when the driver's Python ends. (Dataset.checkpoint would evaluate the frame twice.)
    """
    spark = df.sparkSession
    path = f"{shared_root(spark)}/sizeprofile-frozen-{uuid.uuid4().hex}"
    atexit.register(_remove, spark, path)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
