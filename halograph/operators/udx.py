"""User functions: Arrow-batched scalar and aggregate functions and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def envelope(d2: pd.Series, cutoff: pd.Series) -> pd.Series:
    """Smooth cutoff of a squared distance, in floating point, over whole batches."""
    x = np.clip(d2 / (cutoff * cutoff), 0, 1)
    return (1 - x) ** 2 * (1 + 2 * x)


@F.pandas_udf(T.DoubleType())
def root_mean_square(v: pd.Series) -> float:
    return float(np.sqrt((v.astype(float) ** 2).mean())) if len(v) else 0.0


@F.udtf(returnType=T.StructType([T.StructField(n, T.IntegerType()) for n in ("ox", "oy", "oz")]))
class NeighborBins:
    """The 27 bins around a bin."""

    def eval(self, reach: int):
        for a in range(-reach, reach + 1):
            for b in range(-reach, reach + 1):
                for c in range(-reach, reach + 1):
                    yield a, b, c


def register(spark: SparkSession) -> None:
    """SQL names: neighbor_bins(reach) as a table function, min_image(d, length) as a SQL function."""
    spark.udtf.register("neighbor_bins", NeighborBins)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION min_image(d BIGINT, len BIGINT) RETURNS BIGINT RETURN CASE WHEN d * 2 > len THEN d - len WHEN d * 2 < -len THEN d + len ELSE d END")
