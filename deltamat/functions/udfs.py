"""User-defined functions around the products; the products themselves need none.

They are for semirings that no built-in aggregate can fold, and for packed rows in SQL.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamat.sources.shipping import ship


@F.pandas_udf(T.LongType())
def bits_of(k: pd.Series, ell: pd.Series) -> pd.Series:
    """The fingerprint bit of an inner index."""
    bit = (k.to_numpy(np.int64) % ell.to_numpy(np.int64)).astype(np.uint64)
    return pd.Series((np.uint64(1) << bit).view(np.int64))


@F.arrow_udf(T.LongType())
def times_arrow(a: pa.Array, b: pa.Array) -> pa.Array:
    """⊗ of (+, ·) on Arrow columns."""
    return pc.multiply_checked(a, b)


@F.pandas_udf(T.DoubleType())
def log_sum_exp(v: pd.Series) -> float:
    """A ⊕ without a built-in aggregate: log of the sum of exponentials."""
    x = v.to_numpy(np.float64)
    top = x.max()
    return float(top + np.log(np.exp(x - top).sum()))


@F.udtf(returnType=T.StructType([T.StructField(c, T.LongType()) for c in "ijv"]))
class DcsrRows:
    """Cells of one packed row."""

    def eval(self, i: int, cols: list, vals: list) -> Iterator[tuple]:
        for j, v in zip(cols, vals, strict=True):
            yield i, j, v


def register_udfs(spark: SparkSession) -> None:
    ship(spark)
    spark.udf.register("bits_of", bits_of)
    spark.udf.register("times_arrow", times_arrow)
    spark.udf.register("log_sum_exp", log_sum_exp)
    spark.udtf.register("dcsr_rows", DcsrRows)


def fold_with(terms: DataFrame, udaf=log_sum_exp) -> DataFrame:
    """Products over a semiring whose ⊕ is a grouped user-defined aggregate; terms: (i, j, t)."""
    return terms.groupBy("i", "j").agg(udaf(F.col("t")).alias("v"))
