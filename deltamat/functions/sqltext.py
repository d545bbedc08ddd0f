"""The products as SQL text, for views of cells (i, j, v)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from deltamat.functions.semiring import Semiring


def spgemm_text(a: str, b: str, s: Semiring, trans: tuple[bool, bool] = (False, False)) -> str:
    ai, ak = ("j", "i") if trans[0] else ("i", "j")
    bk, bj = ("j", "i") if trans[1] else ("i", "j")
    value = s.sql_plus.format(s.sql_times.format("a.v", "b.v"))
    return f"SELECT a.{ai} AS i, b.{bj} AS j, {value} AS v FROM {a} a JOIN {b} b ON a.{ak} = b.{bk} GROUP BY a.{ai}, b.{bj}"


def ewise_add_text(x: str, y: str, s: Semiring) -> str:
    return f"SELECT i, j, {s.sql_plus.format('v')} AS v FROM (SELECT i, j, v FROM {x} UNION ALL SELECT i, j, v FROM {y}) t GROUP BY i, j"


def run(spark: SparkSession, text: str, **views: DataFrame) -> DataFrame:
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    return spark.sql(text)
