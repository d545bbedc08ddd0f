"""Index permutations, the block grid, and packed layouts of cells."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from deltamat.sources.shipping import ship


@dataclass(frozen=True)
class Affine:
    """The permutation x -> (a x + b) mod n; a must be coprime to n."""

    n: int
    a: int = 7919
    b: int = 13

    def __post_init__(self):
        from math import gcd

        if gcd(self.a, self.n) != 1:
            raise ValueError(f"{self.a} and {self.n} have a common factor")

    def to(self, x: Column) -> Column:
        return (x * self.a + self.b) % self.n

    def back(self, x: Column) -> Column:
        inverse = pow(self.a, -1, self.n)
        return F.pmod((x - self.b) * inverse, F.lit(self.n))


def permute(m: DataFrame, rows: Affine, cols: Affine) -> DataFrame:
    return m.withColumns({"i": rows.to(F.col("i")), "j": cols.to(F.col("j"))})


def unpermute(m: DataFrame, rows: Affine, cols: Affine) -> DataFrame:
    return m.withColumns({"i": rows.back(F.col("i")), "j": cols.back(F.col("j"))})


def hash_order(index: DataFrame, column: str, seed: int) -> DataFrame:
    """(column, key): a random order of the indices by hash, for range partitioning; no global rank."""
    return index.select(column).distinct().withColumn("key", F.xxhash64(F.lit(seed), column))


@dataclass(frozen=True)
class Grid:
    """qr × qc blocks of contiguous index ranges, after the given permutations (None: as they are)."""

    n: int
    m: int
    qr: int
    qc: int | None = None
    rows: Affine | None = None
    cols: Affine | None = None

    def bi(self, i: Column) -> Column:
        at = self.rows.to(i) if self.rows else i
        return F.floor(at * self.qr / self.n).cast("int")

    def bj(self, j: Column) -> Column:
        at = self.cols.to(j) if self.cols else j
        return F.floor(at * (self.qc or self.qr) / self.m).cast("int")


def assign_grid(m: DataFrame, g: Grid) -> DataFrame:
    return m.withColumns({"bi": g.bi(F.col("i")), "bj": g.bj(F.col("j"))})


def to_dcsr(m: DataFrame, g: Grid) -> DataFrame:
    """A record for each non-empty row of a block: (bi, bj, i, cols, vals); order as it comes."""
    packed = assign_grid(m, g).groupBy("bi", "bj", "i").agg(F.collect_list(F.struct("j", "v")).alias("c"))
    return packed.select("bi", "bj", "i", F.transform("c", lambda x: x["j"]).alias("cols"), F.transform("c", lambda x: x["v"]).alias("vals"))


def from_dcsr(d: DataFrame) -> DataFrame:
    return d.select("i", F.inline(F.arrays_zip(F.col("cols").alias("j"), F.col("vals").alias("v"))))


def to_dcsc(m: DataFrame, g: Grid) -> DataFrame:
    """The column twin: (bi, bj, j, rows, vals)."""
    packed = assign_grid(m, g).groupBy("bi", "bj", "j").agg(F.collect_list(F.struct("i", "v")).alias("c"))
    return packed.select("bi", "bj", "j", F.transform("c", lambda x: x["i"]).alias("rows"), F.transform("c", lambda x: x["v"]).alias("vals"))


def from_dcsc(d: DataFrame) -> DataFrame:
    return d.select(F.col("j"), F.inline(F.arrays_zip(F.col("rows").alias("i"), F.col("vals").alias("v")))).select("i", "j", "v")


def to_csr(m: DataFrame, g: Grid) -> DataFrame:
    """One record for each block: (bi, bj, first_row, row_ptr, cols, vals), rows without cells included.

    A block is packed in one task, so the grid's size must keep blocks within a task's memory.
    """
    if g.rows or g.cols:
        raise ValueError("pack a permuted matrix by permuting its cells first")
    n, qr = g.n, g.qr

    def pack(key: tuple, t: pa.Table) -> pa.Table:
        block = key[0].as_py()
        first, end = -(-block * n // qr), -(-(block + 1) * n // qr)
        t = t.sort_by([("i", "ascending"), ("j", "ascending")])
        ptr = np.searchsorted(t.column("i").to_numpy(), np.arange(first, end + 1))
        one = lambda x: pa.array([x])
        return pa.table({"bi": pa.array([block], pa.int32()), "bj": pa.array([key[1].as_py()], pa.int32()), "first_row": one(first), "row_ptr": one(ptr.tolist()), "cols": one(t.column("j").to_pylist()), "vals": one(t.column("v").to_pylist())})

    kind = m.schema["v"].dataType.simpleString()
    schema = f"bi int, bj int, first_row long, row_ptr array<long>, cols array<long>, vals array<{kind}>"
    ship(m.sparkSession)
    return assign_grid(m, g).select("bi", "bj", "i", "j", "v").groupBy("bi", "bj").applyInArrow(pack, schema)


def csr_row_pointers(m: DataFrame, g: Grid) -> DataFrame:
    """(bi, bj, i, start, end) for each non-empty row: the pointers as a running sum within the block."""
    per_row = assign_grid(m, g).groupBy("bi", "bj", "i").agg(F.count("*").alias("n"))
    w = Window.partitionBy("bi", "bj").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    return per_row.withColumn("end", F.sum("n").over(w)).select("bi", "bj", "i", (F.col("end") - F.col("n")).alias("start"), "end")


def from_csr(c: DataFrame) -> DataFrame:
    row = F.posexplode(F.slice("row_ptr", F.lit(1), F.size("row_ptr") - 1)).alias("r", "start")
    rows = c.select("first_row", "row_ptr", "cols", "vals", row).withColumn("end", F.element_at("row_ptr", F.col("r") + 2))
    rows = rows.where("end > start").select((F.col("first_row") + F.col("r")).alias("i"), F.slice("cols", (F.col("start") + 1).cast("int"), (F.col("end") - F.col("start")).cast("int")).alias("j"), F.slice("vals", (F.col("start") + 1).cast("int"), (F.col("end") - F.col("start")).cast("int")).alias("v"))
    return rows.select("i", F.inline(F.arrays_zip("j", "v")))


def layout_words(m: DataFrame, g: Grid) -> DataFrame:
    """Words that each layout needs: index and value words, by the counts of the blocks."""
    blocks = assign_grid(m, g).groupBy("bi", "bj").agg(F.count("*").alias("nnz"), F.count_distinct("i").alias("nzr"), F.count_distinct("j").alias("nzc"))
    total = blocks.agg(F.sum("nnz").alias("nnz"), F.sum(F.col("nzr") * 2 + 1).alias("dr"), F.sum(F.col("nzc") * 2 + 1).alias("dc"))
    rows = g.qr * (g.qc or g.qr) + g.n * (g.qc or g.qr)
    kinds = F.array(
        F.struct(F.lit("coo").alias("kind"), (F.col("nnz") * 3).alias("words")),
        F.struct(F.lit("csr").alias("kind"), (F.col("nnz") * 2 + rows).alias("words")),
        F.struct(F.lit("dcsr").alias("kind"), (F.col("nnz") * 2 + F.col("dr")).alias("words")),
        F.struct(F.lit("dcsc").alias("kind"), (F.col("nnz") * 2 + F.col("dc")).alias("words")),
    )
    return total.select(F.inline(kinds))


def thread_buckets(m: DataFrame, threads: int) -> DataFrame:
    """Cells for each of the threads that share a block's rows by remainder."""
    return m.groupBy(F.pmod("i", F.lit(threads)).cast("int").alias("thread")).agg(F.count("*").alias("nnz"))
