"""The function surface for SQL users: vectorised, aggregate and table functions.  The engine itself uses none of them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StructType

from .special import digamma_np, log_gamma_np


@pandas_udf(DoubleType())
def digamma_pandas(x: pd.Series) -> pd.Series:
    return pd.Series(digamma_np(x.to_numpy(float)))


@pandas_udf(DoubleType())
def log_gamma_pandas(x: pd.Series) -> pd.Series:
    return pd.Series(log_gamma_np(x.to_numpy(float)))


@pandas_udf(DoubleType())
def log_sum_exp(x: pd.Series) -> float:
    top = x.max()
    return float(top + np.log(np.exp(x - top).sum()))


@udtf(returnType=StructType().add("idx", LongType()))
class PlateRange:
    """Members of a plate: lo, lo + 1, ... hi - 1."""

    def eval(self, lo: int, hi: int):
        for i in range(lo, hi):
            yield (i,)


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL as digamma, log_gamma, log_sum_exp and plate_range."""
    spark.udf.register("digamma", digamma_pandas)
    spark.udf.register("log_gamma", log_gamma_pandas)
    spark.udf.register("log_sum_exp", log_sum_exp)
    spark.udtf.register("plate_range", PlateRange)


__all__ = ["PlateRange", "digamma_pandas", "log_gamma_pandas", "log_sum_exp", "register"]
