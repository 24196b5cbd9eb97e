"""Aggregate functions in Arrow batches, for groups of bounded size; also by name in SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType, LongType

from .isotonic import lower_median as _of_histogram


@pandas_udf(LongType())
def emd_agg(size: pd.Series, truth: pd.Series, est: pd.Series) -> int:
    """Earth mover's distance of two histograms given as rows of a size and its two counts, in any order.

    A null count is 0. The frame form (`metrics.emd`) is for groups too large for one task.
    """
    order = np.argsort(size.to_numpy(), kind="stable")
    at = size.to_numpy()[order].astype(np.int64)
    gap = np.cumsum((est.fillna(0).to_numpy(dtype=np.int64) - truth.fillna(0).to_numpy(dtype=np.int64))[order])
    return int(np.abs(gap[:-1]) @ np.diff(at)) if len(at) else 0


@pandas_udf(DoubleType())
def lower_median(x: pd.Series) -> float:
    """The smaller of the two middle values; nulls are left out, none left: null."""
    values, counts = np.unique(x.dropna().to_numpy(dtype=float), return_counts=True)
    return float(_of_histogram(values, counts)) if len(values) else None


def register(spark: SparkSession) -> None:
    """sp_emd(size, truth, est) and sp_lower_median(x)."""
    spark.udf.register("sp_emd", emd_agg)
    spark.udf.register("sp_lower_median", lower_median)
