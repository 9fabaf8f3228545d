"""Python functions registered with Spark, and SQL helpers."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructType


@pandas_udf(DoubleType())
def cosine_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.stack(a.to_numpy()), np.stack(b.to_numpy())
    return pd.Series((x * y).sum(axis=1) / np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1)))


@pandas_udf(DoubleType())
def mean_udf(v: pd.Series) -> float:
    return float(v.mean())


@udtf(returnType=StructType().add("scale", IntegerType()).add("lo", LongType()).add("hi", LongType()))
class scales_udtf:
    """One row for each scale (2^k, 2^(k+1)] from log beta to the greatest distance."""

    def eval(self, max_dist: int, beta: int):
        k = max(0, int(beta).bit_length() - 1)
        while 2**k < max_dist:
            yield k, 2**k, 2 ** (k + 1)
            k += 1


def register(spark: SparkSession) -> None:
    """SQL helpers as SQL functions, so that they stay inside Catalyst: uniform bits and rounding up by num/den."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hop_u32(x STRING) RETURNS BIGINT RETURN CAST(conv(substring(md5(x), 1, 8), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hop_round(w BIGINT, num BIGINT, den BIGINT) RETURNS BIGINT RETURN (w * den + num - 1) div num")
