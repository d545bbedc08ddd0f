"""Batches of changes: building, classifying, moving and applying them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamat.functions.semiring import PLUS_TIMES, Semiring
from deltamat.operators.layout import Grid
from deltamat.operators.matrix import ewise_add

OPS = ("add", "set", "del")


@dataclass(frozen=True)
class UpdateBatch:
    """Rows (i, j, v, op, seq); of several rows for a cell the last by seq holds, adds are ⊕-combined.

    Ties of seq go to the row that sorts last by (op, v). A batch may be empty. plain: a batch built
    without op, of sets only, which need no join to be resolved.
    """

    rows: DataFrame
    batch_id: int = 0
    plain: bool = False

    @classmethod
    def build(cls, df: DataFrame, batch_id: int = 0) -> UpdateBatch:
        have = set(df.columns)
        op = F.col("op") if "op" in have else F.lit("set")
        seq = F.col("seq") if "seq" in have else F.lit(0)
        value = F.col("v") if "v" in have else F.lit(1)
        return cls(df.select(F.col("i").cast("long"), F.col("j").cast("long"), value.alias("v"), op.alias("op"), seq.cast("long").alias("seq")).where("i is not null and j is not null"), batch_id, "op" not in have)

    def last(self, s: Semiring = PLUS_TIMES) -> DataFrame:
        """(i, j, op, v): one row for each cell, in which the batch's rows for it are resolved.

        The last set or delete holds; adds after it (by seq) are ⊕-combined with it, or among
        themselves where there is none.
        """
        order = F.struct("seq", "op", "v")
        if self.plain:
            only = self.rows.groupBy("i", "j").agg(F.max_by(F.struct("op", "v"), order).alias("x"))
            return only.select("i", "j", F.col("x.op").alias("op"), F.col("x.v").alias("v"))
        fixed = self.rows.where("op <> 'add'").groupBy("i", "j").agg(F.max_by(F.struct("op", "v", "seq"), order).alias("x"))
        fixed = fixed.select("i", "j", F.col("x.op").alias("op"), F.col("x.v").alias("v"), F.col("x.seq").alias("at"))
        adds = self.rows.where("op = 'add'").join(fixed.select("i", "j", "at"), ["i", "j"], "left").where("at is null or seq > at")
        adds = adds.groupBy("i", "j").agg(s.plus_agg(F.col("v")).alias("added"))
        both = fixed.join(adds, ["i", "j"], "full")
        new = F.when(F.col("added").isNull(), F.col("v")).when((F.col("op") == "set") & F.col("v").isNotNull(), s.plus(F.col("v"), F.col("added"))).otherwise(F.col("added"))
        op = F.when(F.col("op").isNull(), "add").when(F.col("added").isNotNull(), "set").otherwise(F.col("op"))
        return both.select("i", "j", op.alias("op"), new.alias("v"))

    def added(self, s: Semiring = PLUS_TIMES) -> DataFrame:
        """The update matrix of the adds."""
        return self.rows.where("op = 'add'").groupBy("i", "j").agg(s.plus_agg(F.col("v")).alias("v"))

    def pattern(self) -> DataFrame:
        return self.rows.select("i", "j").distinct()


def apply_add(a: DataFrame, star: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return ewise_add(a, star, s)


def apply_merge(a: DataFrame, star: DataFrame) -> DataFrame:
    """Cells of star replace those of a, or are inserted."""
    return a.select("i", "j", "v").join(star.select("i", "j"), ["i", "j"], "left_anti").unionByName(star.select("i", "j", "v"))


def apply_mask(a: DataFrame, star: DataFrame) -> DataFrame:
    """Cells of a where star stores one are deleted."""
    return a.select("i", "j", "v").join(star.select("i", "j"), ["i", "j"], "left_anti")


def apply_ops(a: DataFrame, batch: UpdateBatch, s: Semiring = PLUS_TIMES) -> DataFrame:
    """A mixed batch: the last row of each cell deletes it, sets it or is added to it."""
    last = batch.last(s).select("i", "j", "op", F.col("v").alias("u"))
    both = a.select("i", "j", "v").join(last, ["i", "j"], "full")
    new = F.when(F.col("op").isNull(), F.col("v")).when(F.col("op") == "set", F.col("u")).when(F.col("op") == "add", F.when(F.col("v").isNull(), F.col("u")).otherwise(s.plus(F.col("v"), F.col("u"))))
    return both.select("i", "j", new.alias("v")).where("v is not null")


def delta_of(new: DataFrame, old: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """The update matrix A' − A of a ring; cells that did not change are left out."""
    if not s.is_ring:
        raise ValueError(f"{s.name} has no subtraction")
    zero = F.lit(s.zero)
    both = new.select("i", "j", F.col("v").alias("x")).join(old.select("i", "j", F.col("v").alias("y")), ["i", "j"], "full")
    return both.select("i", "j", s.minus(F.coalesce("x", zero), F.coalesce("y", zero)).alias("v"), "x", "y").where("not (x <=> y)").select("i", "j", "v")


def changed_pattern(new: DataFrame, old: DataFrame) -> DataFrame:
    both = new.select("i", "j", F.col("v").alias("x")).join(old.select("i", "j", F.col("v").alias("y")), ["i", "j"], "full")
    return both.where("not (x <=> y)").select("i", "j")


def reasons(a: DataFrame, batch: UpdateBatch, s: Semiring = PLUS_TIMES) -> DataFrame:
    """(reason, n): why cells of the batch can or cannot be written as an addition."""
    last = batch.last(s).select("i", "j", "op", F.col("v").alias("u"))
    seen = last.join(a.select("i", "j", "v"), ["i", "j"], "left")
    absent, same = F.col("v").isNull(), F.col("v").eqNullSafe(F.col("u"))
    if s.is_ring:
        why = F.when(F.col("op") == "add", "add").otherwise("difference")
    else:
        absorbed = s.plus(F.col("v"), F.col("u")).eqNullSafe(F.col("u"))
        added = F.when(absent | F.lit(s.distributive), "add").otherwise("replace")
        absorbed = absorbed & F.lit(s.distributive)
        why = F.when(F.col("op") == "add", added).when(F.col("op") == "del", F.when(absent, "nothing").otherwise("delete")).when(absent, "insert").when(same, "nothing").when(absorbed, "absorbs").otherwise("replace")
    return seen.groupBy(why.alias("reason")).agg(F.count("*").alias("n"))


def additions(a: DataFrame, batch: UpdateBatch, s: Semiring) -> DataFrame:
    """The update matrix A* with A' = A ⊕ A*, for a batch that classify() calls algebraic.

    In a ring that is the difference. Elsewhere adds give what they add, and sets the new value, which
    stands where nothing did or takes up the old one (old ⊕ new = new); a set to the value that is
    there gives nothing, since ⊕ need not be idempotent.
    """
    if s.is_ring:
        touched = a.select("i", "j", "v").join(batch.pattern(), ["i", "j"], "left_semi")
        return delta_of(apply_ops(touched, batch, s), touched, s)
    last = batch.last(s).select("i", "j", "op", F.col("v").alias("u")).where("op <> 'del'")
    seen = last.join(a.select("i", "j", "v"), ["i", "j"], "left")
    return seen.where((F.col("op") == "add") | ~F.col("v").eqNullSafe(F.col("u"))).select("i", "j", F.col("u").alias("v"))


GENERAL = ("delete", "replace")


def classify(a: DataFrame, batch: UpdateBatch, s: Semiring = PLUS_TIMES) -> str:
    """'algebraic' if a ⊕ delta can express the whole batch, else 'general'."""
    return "general" if reasons(a, batch, s).where(F.col("reason").isin(*GENERAL)).limit(1).count() else "algebraic"


def redistribute(star: DataFrame, g: Grid, method: str = "one_step", sources: int = 0) -> DataFrame:
    """The batch with its blocks, dealt to them.

    one_step: one exchange. two_step: first along grid columns to the row, then along the row, with
    the trace (src, mid, dst) of processes numbered row by row. sort: one range exchange and a sort.
    Arrival is by hash over ``sources`` processes (default: the grid's), as updates come from anywhere.
    """
    q, qc = g.qr, g.qc or g.qr
    laid = star.withColumns({"bi": g.bi(F.col("i")), "bj": g.bj(F.col("j"))})
    if method == "one_step":
        return laid.repartition("bi", "bj")
    if method == "sort":
        return laid.repartitionByRange("bi", "bj", "i", "j").sortWithinPartitions("bi", "bj", "i", "j")
    src = F.pmod(arrival(), F.lit(sources or q * qc)).cast("int")
    traced = laid.withColumn("src", src).withColumns({"mid": F.col("bi") * qc + F.pmod("src", F.lit(qc)), "dst": F.col("bi") * qc + F.col("bj")})
    return traced.repartition("mid").repartition("dst")


def arrival():
    """The process number, before the remainder, at which an update is born."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.col("i").cast("string"), F.col("j").cast("string"), F.lit("src"))), 1, 8), 16, 10).cast("long")


