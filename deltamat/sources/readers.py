"""Edge lists and matrices in text, CSV, JSON and Matrix Market form; and their writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CELLS = "i long, j long, v double"


def edge_text(spark: SparkSession, path: str) -> DataFrame:
    """Lines ``u v [w]`` separated by blanks: (i, j, v, malformed); a missing weight is 1.

    Lines that start with # or % and empty lines are left out; what does not parse is marked.
    """
    lines = spark.read.text(path).select(F.trim("value").alias("line")).where("line <> '' and not line rlike '^[#%]'")
    p = F.split("line", r"\s+")
    cells = lines.select(F.try_element_at(p, F.lit(1)).try_cast("long").alias("i"), F.try_element_at(p, F.lit(2)).try_cast("long").alias("j"), F.when(F.size(p) > 2, F.try_element_at(p, F.lit(3)).try_cast("double")).otherwise(1.0).alias("v"), F.size(p).alias("n"))
    return cells.select("i", "j", "v", (F.col("i").isNull() | F.col("j").isNull() | F.col("v").isNull() | ~F.col("n").between(2, 3)).alias("malformed"))


def matrix_market(spark: SparkSession, path: str) -> DataFrame:
    """Cells of a Matrix Market coordinate file, from 0; symmetric files give both triangles.

    The size line is told apart by its place: the first line that is no comment.
    """
    raw = spark.read.text(path).select(F.monotonically_increasing_id().alias("at"), F.trim("value").alias("line")).where("line <> ''")
    banner = raw.where("line like '%%MatrixMarket%'").select(F.lower("line")).first()
    body = raw.where("line not rlike '^%'")
    size_at = body.agg(F.min("at")).first()[0]
    p = F.split("line", r"\s+")
    pattern = banner is not None and "pattern" in banner[0]
    cells = body.where(F.col("at") != size_at).select((p[0].cast("long") - 1).alias("i"), (p[1].cast("long") - 1).alias("j"), (F.lit(1.0) if pattern else p[2].cast("double")).alias("v"))
    if banner is not None and "symmetric" in banner[0]:
        cells = cells.unionByName(cells.where("i <> j").select(F.col("j").alias("i"), F.col("i").alias("j"), "v"))
    return cells


def csv_cells(spark: SparkSession, path: str, header: bool = True) -> DataFrame:
    return spark.read.schema(CELLS).option("header", header).csv(path)


def json_cells(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(CELLS).json(path)


def write_edge_text(cells: DataFrame, path: str) -> None:
    cells.select(F.concat_ws(" ", "i", "j", "v").alias("value")).write.mode("overwrite").text(path)


def write_blocks(laid: DataFrame, path: str) -> None:
    """Parquet by blocks, sorted by row inside, so that rows are found by file statistics."""
    laid.repartition("bi", "bj").sortWithinPartitions("bi", "bj", "i", "j").write.mode("overwrite").partitionBy("bi", "bj").parquet(path)
