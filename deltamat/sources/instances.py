"""Matrix instances on the given tables, reproducible draws, and a generator of power-law graphs.

Draws go by a threshold on a hash of the cell and a seed, never by a global rank, so any engine
with md5 makes the same draw and none needs to sort all cells.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamat.functions.semiring import PLUS_TIMES
from deltamat.operators.matrix import from_df, transpose

#: Draws are whole numbers below this.
PARTS = 1_000_000


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def hash32(*parts: Column) -> Column:
    """The first eight hexadecimal digits of an md5 over the parts, as a number."""
    text = F.concat_ws("|", *[p.cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def draw(cells: DataFrame, seed: int) -> DataFrame:
    """cells with u, a number in 0..PARTS-1 that depends on (i, j, seed) only."""
    return cells.withColumn("u", hash32(F.col("i"), F.col("j"), F.lit(seed)) % PARTS)


def part_supp(spark, d) -> DataFrame:
    return quantities(read(spark, d, "lineitem"), "l_partkey", "l_suppkey")


def order_part(spark, d) -> DataFrame:
    return quantities(read(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def part_order(spark, d) -> DataFrame:
    return quantities(read(spark, d, "lineitem"), "l_partkey", "l_orderkey")


def supp_order(spark, d) -> DataFrame:
    return quantities(read(spark, d, "lineitem"), "l_suppkey", "l_orderkey")


def quantities(lines: DataFrame, i: str, j: str) -> DataFrame:
    return from_df(lines, i, j, "l_quantity", PLUS_TIMES).withColumn("v", F.col("v").cast("long"))


def order_cust(spark, d) -> DataFrame:
    """order × customer, 1."""
    return read(spark, d, "orders").where("o_orderkey is not null and o_custkey is not null").select(F.col("o_orderkey").alias("i"), F.col("o_custkey").alias("j")).distinct().withColumn("v", F.lit(1).cast("long"))


def cust_order(spark, d) -> DataFrame:
    return transpose(order_cust(spark, d)).select("i", "j", "v")


def assignment(spark, d, table: str, key: str, label: str) -> DataFrame:
    """entity × label, 1: the operator that contracts entities to labels."""
    return read(spark, d, table).select(F.col(key).cast("long").alias("i"), F.col(label).cast("long").alias("j")).where("i is not null and j is not null").distinct().withColumn("v", F.lit(1).cast("long"))


def user_prop(spark, d) -> DataFrame:
    """user × props.k, number of events."""
    e = read(spark, d, "events").select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("j"))
    return e.where("i is not null and j is not null").groupBy("i", "j").agg(F.count("*").alias("v"))


def successors(rows: DataFrame, value: str, order: str) -> DataFrame:
    """(i, j): every value and the next one by a unique order, without one task for all rows.

    Rows are dealt by ranges of the order; the last of a range is paired with the first of the next
    non-empty one, and there are only as many of those as ranges.
    """
    from deltamat.sources.scratch import materialize

    ranged = rows.where(f"{order} is not null").select(F.col(order).alias("o"), F.col(value).alias("i")).repartitionByRange("o").withColumn("part", F.spark_partition_id())
    ranged = materialize(ranged, "ranges")
    within = Window.partitionBy("part").orderBy("o")
    inner = ranged.select("part", "i", F.lead("i").over(within).alias("j"), F.row_number().over(Window.partitionBy("part").orderBy(F.desc("o"))).alias("back"))
    ends = ranged.groupBy("part").agg(F.min_by("i", "o").alias("first")).select("part", F.lead("first").over(Window.orderBy("part")).alias("next"))
    linked = inner.join(F.broadcast(ends), "part").select("i", F.when(F.col("back") == 1, F.col("next")).otherwise(F.col("j")).alias("j"))
    return linked.where("i is not null and j is not null")


def user_succ(spark, d) -> DataFrame:
    """user × user of the next event, number of times; square."""
    return successors(read(spark, d, "events"), "user_id", "event_id").groupBy("i", "j").agg(F.count("*").alias("v"))


def doc_term(spark, d, least_df: int = 2, most_df: int | None = None) -> DataFrame:
    """doc × term (64-bit hash), frequency; terms are lower-case runs of letters and digits."""
    words = read(spark, d, "documents").select(F.col("doc_id").alias("i"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"([a-z0-9]+)"), F.lit(1))).alias("w"))
    cells = words.groupBy("i", F.xxhash64("w").alias("j")).agg(F.count("*").alias("v"))
    df = cells.groupBy("j").agg(F.count("*").alias("df")).where(F.col("df") >= least_df)
    if most_df:
        df = df.where(F.col("df") <= most_df)
    return cells.join(df.select("j"), "j", "left_semi").select("i", "j", "v")


def page_link(spark, d) -> DataFrame:
    """page × link target (hash), number of links."""
    links = read(spark, d, "pages").select(F.col("page_id").alias("i"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)'), F.lit(1))).alias("target"))
    return links.groupBy("i", F.xxhash64("target").alias("j")).agg(F.count("*").alias("v"))


def turn_role(spark, d) -> DataFrame:
    return read(spark, d, "conversations").groupBy(F.col("conv_id").alias("i"), F.xxhash64("role").alias("j")).agg(F.count("*").alias("v"))


def vec_dim(spark, d, least: float = 0.0) -> DataFrame:
    """vector × dimension, components above a threshold, in thousandths."""
    e = read(spark, d, "embeddings").select(F.col("vec_id").alias("i"), F.posexplode("embedding").alias("j", "x"))
    return e.where(F.col("x") > least).select("i", F.col("j").cast("long").alias("j"), F.round(F.col("x").cast("double") * 1000).cast("long").alias("v"))


def vec_label(spark, d) -> DataFrame:
    return assignment(spark, d, "embeddings", "vec_id", "label")


def trade(spark, d) -> DataFrame:
    """customer nation × supplier nation, quantity."""
    li = read(spark, d, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    o = read(spark, d, "orders").select("o_orderkey", "o_custkey")
    c = read(spark, d, "customer").select("c_custkey", "c_nationkey")
    s = read(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(s, li.l_suppkey == s.s_suppkey)
    return quantities(j, "c_nationkey", "s_nationkey")


#: Upper bounds, out of 256, of the first three quadrants of the usual power-law graph.
QUADRANTS = (146, 195, 243)


def rmat(spark: SparkSession, scale: int, edges: int, seed: int = 1) -> DataFrame:
    """(e, i, j): a power-law graph on 2**scale vertices, each edge from its own md5 digests."""
    return rmat_of(spark.range(edges).select(F.col("id").alias("e")), scale, seed)


def rmat_of(ids: DataFrame, scale: int, seed: int = 1) -> DataFrame:
    """rmat() with an edge for every row (e) of a table of whole numbers."""
    i, j = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        digest = F.md5(F.concat_ws("|", F.col("e").cast("string"), F.lit(str(seed + level // 16))))
        at = level % 16
        x = F.conv(F.substring(digest, 2 * at + 1, 2), 16, 10).cast("long")
        i = i * 2 + F.when(x >= QUADRANTS[1], 1).otherwise(0)
        j = j * 2 + F.when((x >= QUADRANTS[0]) & (x < QUADRANTS[1]) | (x >= QUADRANTS[2]), 1).otherwise(0)
    return ids.select("e", i.alias("i"), j.alias("j"))


def dims(spark, d, *tables: tuple[str, str]) -> list[int]:
    """Index bounds of key columns: largest key and one more."""
    return [read(spark, d, t).agg(F.coalesce(F.max(k), F.lit(-1))).first()[0] + 1 for t, k in tables]
