"""Sparse matrices as tables of cells (i, j, v), and the operations that need no product.

A stored cell is a structural non-zero, whatever its value; an absent one is the semiring's zero.
Null is no value: cells with a null index or value are not cells and are left out on construction.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from deltamat.functions.semiring import PLUS_TIMES, Semiring
from deltamat.sources.scratch import materialize

CELL = ("i", "j")


def from_df(df: DataFrame, i: str | Column, j: str | Column, v: str | Column, s: Semiring = PLUS_TIMES, dup: str = "plus", seq: str | None = None) -> DataFrame:
    """Cells from triples; duplicates are ⊕-combined, the last by ``seq`` wins, or they are an error."""
    col = lambda c: F.col(c) if isinstance(c, str) else c
    order = [F.col(seq).alias("seq")] if seq else []
    t = df.select(col(i).cast("long").alias("i"), col(j).cast("long").alias("j"), col(v).alias("v"), *order).where("i is not null and j is not null and v is not null")
    g = t.groupBy("i", "j")
    if dup == "plus":
        return g.agg(s.plus_agg(F.col("v")).alias("v"))
    if dup == "last":
        return g.agg(F.max_by("v", F.struct("seq", "v")).alias("v"))
    bad = F.raise_error(F.concat_ws(" ", F.lit("duplicate cell"), F.col("i"), F.col("j")))
    return g.agg(F.count("*").alias("n"), F.first("v").alias("v")).select("i", "j", F.when(F.col("n") == 1, F.col("v")).otherwise(bad.cast(t.schema["v"].dataType)).alias("v"))


def symmetrize(m: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """Both directions of every edge, self-loops once."""
    back = m.where("i <> j").select(F.col("j").alias("i"), F.col("i").alias("j"), "v")
    return m.select("i", "j", "v").unionByName(back).groupBy("i", "j").agg(s.plus_agg(F.col("v")).alias("v"))


def ewise_add(x: DataFrame, y: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return x.select("i", "j", "v").unionByName(y.select("i", "j", "v")).groupBy("i", "j").agg(s.plus_agg(F.col("v")).alias("v"))


def ewise_mult(x: DataFrame, y: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    both = x.select("i", "j", F.col("v").alias("x")).join(y.select("i", "j", F.col("v").alias("y")), ["i", "j"])
    return both.select("i", "j", s.times(F.col("x"), F.col("y")).alias("v"))


def scale(x: DataFrame, alpha, s: Semiring = PLUS_TIMES) -> DataFrame:
    return x.select("i", "j", s.times(F.lit(alpha), F.col("v")).alias("v"))


def apply(x: DataFrame, fn) -> DataFrame:
    return x.select("i", "j", fn(F.col("v")).alias("v"))


def select(x: DataFrame, predicate: Column | str) -> DataFrame:
    return x.where(predicate)


def tril(x: DataFrame) -> DataFrame:
    return x.where("i > j")


def triu(x: DataFrame) -> DataFrame:
    return x.where("i < j")


def diag(x: DataFrame) -> DataFrame:
    return x.where("i = j")


def offdiag(x: DataFrame) -> DataFrame:
    return x.where("i <> j")


def transpose(x: DataFrame) -> DataFrame:
    rest = [c for c in x.columns if c not in CELL]
    return x.select(F.col("j").alias("i"), F.col("i").alias("j"), *rest)


def positions(index: DataFrame, name: str) -> DataFrame:
    """(name, _to): distinct indices numbered from 0 in their order, range by range; no task sees them all.

    Only the ranges' sizes, one number for each partition, meet in one place.
    """
    ranged = materialize(index.select(name).distinct().repartitionByRange(name).withColumn("_part", F.spark_partition_id()), "ranges")
    sizes = ranged.groupBy("_part").agg(F.count("*").alias("_n"))
    before = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_before"))
    inner = F.row_number().over(Window.partitionBy("_part").orderBy(name))
    return ranged.withColumn("_at", inner).join(F.broadcast(before), "_part").select(name, (F.col("_before") + F.col("_at") - 1).alias("_to"))


def extract(x: DataFrame, rows: DataFrame | None = None, cols: DataFrame | None = None, relabel: bool = False) -> DataFrame:
    """The submatrix of rows(i) and cols(j); relabel numbers the kept indices from 0 in their order.

    Relabelling numbers the given index lists by ranges, see positions().
    """
    for names, index in (("i", rows), ("j", cols)):
        if index is None:
            continue
        index = index.select(names).distinct()
        if relabel:
            x = x.join(positions(index, names), names).drop(names).withColumn(names, F.col("_to").cast("long")).drop("_to")
        else:
            x = x.join(index, names, "left_semi")
    return x.select("i", "j", "v")


def assign(x: DataFrame, sub: DataFrame, rows: DataFrame, cols: DataFrame) -> DataFrame:
    """x with the region rows × cols replaced by ``sub``."""
    marked = x.join(rows.select("i").distinct().withColumn("_r", F.lit(True)), "i", "left").join(cols.select("j").distinct().withColumn("_c", F.lit(True)), "j", "left")
    return marked.where("_r is null or _c is null").select("i", "j", "v").unionByName(sub.select("i", "j", "v"))


def reduce_rows(x: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return x.groupBy("i").agg(s.plus_agg(F.col("v")).alias("v"))


def reduce_cols(x: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return x.groupBy("j").agg(s.plus_agg(F.col("v")).alias("v"))


def reduce_all(x: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return x.agg(s.plus_agg(F.col("v")).alias("v"))


def degrees(x: DataFrame, by: str = "i") -> DataFrame:
    return x.groupBy(by).agg(F.count("*").alias("deg"))


def degree_histogram(x: DataFrame, by: str = "i") -> DataFrame:
    return degrees(x, by).groupBy("deg").agg(F.count("*").alias("n"))


def identity(spark: SparkSession, n: int, one=1) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("i"), F.col("id").alias("j"), F.lit(one).cast("long").alias("v"))


def empty(spark: SparkSession, value: str = "long") -> DataFrame:
    return spark.createDataFrame([], f"i long, j long, v {value}")


def diag_of(vector: DataFrame) -> DataFrame:
    return vector.select("i", F.col("i").alias("j"), "v")


def ones_pattern(x: DataFrame) -> DataFrame:
    return x.select("i", "j", F.lit(1).cast("long").alias("v"))


def spmv(a: DataFrame, x: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """A·x for a vector x(i, v)."""
    right = x.select(F.col("i").alias("j"), F.col("v").alias("xv"))
    return a.join(right, "j").groupBy("i").agg(s.plus_agg(s.times(F.col("v"), F.col("xv"))).alias("v"))


def vxm(x: DataFrame, a: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """xᵀ·A as a vector (i, v)."""
    left = x.select("i", F.col("v").alias("xv"))
    return a.join(left, "i").groupBy("j").agg(s.plus_agg(s.times(F.col("xv"), F.col("v"))).alias("v")).select(F.col("j").alias("i"), "v")


KRONECKER_CELLS = 100_000


def kronecker(x: DataFrame, y: DataFrame, y_rows: int, y_cols: int, s: Semiring = PLUS_TIMES) -> DataFrame:
    """x ⊗ y for small factors: the second is broadcast and must have few cells."""
    if y.limit(KRONECKER_CELLS + 1).count() > KRONECKER_CELLS:
        raise ValueError("the second factor is too large to pair with every cell")
    r = y.select(F.collect_list(F.struct(F.col("i").alias("yi"), F.col("j").alias("yj"), F.col("v").alias("yv"))).alias("ys"))
    paired = x.crossJoin(F.broadcast(r)).select("i", "j", "v", F.explode("ys").alias("y"))
    return paired.select((F.col("i") * y_rows + F.col("y.yi")).alias("i"), (F.col("j") * y_cols + F.col("y.yj")).alias("j"), s.times(F.col("v"), F.col("y.yv")).alias("v"))


def hstack(x: DataFrame, y: DataFrame, x_cols: int) -> DataFrame:
    return x.select("i", "j", "v").unionByName(y.select("i", (F.col("j") + x_cols).alias("j"), "v"))


def vstack(x: DataFrame, y: DataFrame, x_rows: int) -> DataFrame:
    return x.select("i", "j", "v").unionByName(y.select((F.col("i") + x_rows).alias("i"), "j", "v"))


def bipartite(x: DataFrame, n_rows: int) -> DataFrame:
    """The square matrix [[0, x], [xᵀ, 0]]."""
    shifted = x.select("i", (F.col("j") + n_rows).alias("j"), "v")
    return shifted.unionByName(transpose(shifted))


def normalize(x: DataFrame, by: str = "j") -> DataFrame:
    """Values as shares of their row's (by='i') or column's (by='j') sum; sums of 0 give no cells."""
    total = x.groupBy(by).agg(F.sum("v").alias("_t")).where("_t <> 0")
    return x.join(total, by).select("i", "j", (F.col("v") / F.col("_t")).alias("v"))


def topk_per_row(x: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("i").orderBy(F.desc("v"), "j")
    return x.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def prune_zeros(x: DataFrame, zero=0) -> DataFrame:
    return x.where(F.col("v") != F.lit(zero))


def resize(x: DataFrame, n: int, m: int) -> DataFrame:
    return x.where((F.col("i") < n) & (F.col("j") < m))


def dictionary_encode(df: DataFrame, column: str) -> tuple[DataFrame, DataFrame]:
    """(df with ``<column>_id``, dictionary): ids are 64-bit hashes, and a collision is an error."""
    words = df.select(F.col(column).alias("key")).where("key is not null").distinct()
    d = words.groupBy(F.xxhash64("key").alias("id")).agg(F.min("key").alias("key"), F.max("key").alias("_m"))
    clash = F.raise_error(F.lit("two keys share one id")).cast("long")
    d = d.select(F.when(F.col("key") == F.col("_m"), F.col("id")).otherwise(clash).alias("id"), "key")
    return df.withColumn(f"{column}_id", F.when(F.col(column).isNotNull(), F.xxhash64(column))), d


def diff(x: DataFrame, y: DataFrame, zero=None, tol: float | None = None) -> DataFrame:
    """(i, j, x, y, kind) of differing cells: missing (only in y), extra (only in x) or value.

    zero: stored zeros count as absent (else they are cells); tol: greatest difference allowed.
    """
    if zero is not None:
        x, y = prune_zeros(x, zero), prune_zeros(y, zero)
    both = x.select("i", "j", F.col("v").alias("x")).join(y.select("i", "j", F.col("v").alias("y")), ["i", "j"], "full")
    same = F.col("x").eqNullSafe(F.col("y")) if tol is None else F.coalesce(F.abs(F.col("x") - F.col("y")) <= tol, F.lit(False))
    kind = F.when(F.col("x").isNull(), "missing").when(F.col("y").isNull(), "extra").otherwise("value")
    return both.where(~same).withColumn("kind", kind)


def equals(x: DataFrame, y: DataFrame, zero=None, tol: float | None = None) -> bool:
    return diff(x, y, zero, tol).isEmpty()


def counts(x: DataFrame, zero=0) -> DataFrame:
    """Stored cells, cells other than zero, and how many rows and columns hold any."""
    return x.agg(
        F.count("*").alias("nnz"),
        F.count_if(F.col("v") != F.lit(zero)).alias("nnz_numerical"),
        F.count_distinct("i").alias("nz_rows"),
        F.count_distinct("j").alias("nz_cols"),
    )


@dataclass(frozen=True)
class SparseMatrix:
    """Cells with their dimensions, semiring and kind: dynamic, static or update."""

    cells: DataFrame
    n_rows: int
    n_cols: int
    semiring: Semiring = PLUS_TIMES
    kind: str = "dynamic"
    orientation: str = "row"
    version: int = 0

    @classmethod
    def build(cls, df, i, j, v, dims, s: Semiring = PLUS_TIMES, dup="plus", seq=None, **more) -> SparseMatrix:
        return cls(from_df(df, i, j, v, s, dup, seq), *dims, s, **more)

    def with_cells(self, cells: DataFrame) -> SparseMatrix:
        return replace(self, cells=cells, version=self.version + 1)

    @property
    def T(self) -> SparseMatrix:
        turned = "col" if self.orientation == "row" else "row"
        return replace(self, cells=transpose(self.cells), n_rows=self.n_cols, n_cols=self.n_rows, orientation=turned)

    def as_update(self) -> SparseMatrix:
        return replace(self, kind="update")

    def nnz(self, structural: bool = True) -> int:
        return (self.cells if structural else prune_zeros(self.cells, self.semiring.zero)).count()

    def is_hypersparse(self, ratio: float = 0.1) -> bool:
        n = self.nnz()
        return n <= ratio * self.n_rows and n <= ratio * self.n_cols

    def resized(self, n: int, m: int) -> SparseMatrix:
        return replace(self, cells=resize(self.cells, n, m), n_rows=n, n_cols=m)
