"""Products kept correct under any change: recompute only the cells that can have changed.

The pattern C* of such cells comes from the deltas' structure. Each stored result cell carries a
fingerprint: one bit (of ell) for each inner index of its terms, whether or not it decided the
value. The bits of a row's changed cells tell which columns of that row of A' are needed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamat.functions.semiring import Semiring, bit_of
from deltamat.operators.multiply import BROADCAST_CELLS, fits, sides
from deltamat.sources.scratch import materialize

VARIANTS = ("bits", "none", "rows", "exact")


def product_with_bits(a: DataFrame, b: DataFrame, s: Semiring, ell: int = 64, trans=(False, False)) -> DataFrame:
    """(i, j, v, bits): value and fingerprint of every result cell, in one aggregate."""
    left, right = sides(a, b, trans)
    return with_bits(left.join(right, "k"), s, ell)


def with_bits(terms: DataFrame, s: Semiring, ell: int) -> DataFrame:
    value = s.plus_agg(s.times(F.col("av"), F.col("bv"))).alias("v")
    return terms.groupBy("i", "j").agg(value, F.bit_or(bit_of(F.col("k"), ell)).alias("bits"))


def structure(a: DataFrame, b: DataFrame, small: str, trans, cells: int) -> DataFrame:
    """(i, j, k) of all terms; values are not read."""
    left, right = sides(a.select("i", "j", F.lit(1).alias("v")), b.select("i", "j", F.lit(1).alias("v")), trans)
    left, right = left.select("i", "k"), right.select("k", "j")
    if small == "left":
        left = F.broadcast(left) if fits(left, cells) else left
    else:
        right = F.broadcast(right) if fits(right, cells) else right
    return left.join(right, "k")


def compute_pattern(a_old: DataFrame, a_star: DataFrame | None, b_new: DataFrame, b_star: DataFrame | None, ell: int = 64, trans=(False, False), cells: int = BROADCAST_CELLS) -> DataFrame:
    """(i, j, bits): cells that can have changed, with the bits of the deltas' terms.

    A* meets the new B and B* the old A: a term that loses both factors in one batch is still seen.
    """
    terms = []
    if a_star is not None:
        terms.append(structure(a_star, b_new, "left", trans, cells))
    if b_star is not None:
        terms.append(structure(a_old, b_star, "right", trans, cells))
    both = terms[0] if len(terms) == 1 else terms[0].unionByName(terms[1])
    return both.groupBy("i", "j").agg(F.bit_or(bit_of(F.col("k"), ell)).alias("bits"))


def needed_bits(c: DataFrame, c_star: DataFrame) -> DataFrame:
    """E: the old and the delta's bits, at the cells of C* only."""
    old = c.select("i", "j", F.col("bits").alias("old"))
    return c_star.join(old, ["i", "j"], "left").select("i", "j", F.col("bits").bitwiseOR(F.coalesce("old", F.lit(0).cast("long"))).alias("bits"))


def sized(df: DataFrame, cells: int = BROADCAST_CELLS) -> DataFrame:
    """The table, marked for broadcast if it is checked to be small enough."""
    return F.broadcast(df) if fits(df, cells) else df


def rows_needed(c: DataFrame, c_star: DataFrame, by: str = "i") -> DataFrame:
    """row_bits() of needed_bits(), made without moving C where C* is small: C is scanned in place."""
    cells = sized(c_star.select("i", "j"))
    old = c.join(cells, ["i", "j"], "left_semi").select(by, "bits")
    return c_star.select(by, "bits").unionByName(old).groupBy(by).agg(F.bit_or("bits").alias("bits"))


def row_bits(e: DataFrame, by: str = "i") -> DataFrame:
    return e.groupBy(by).agg(F.bit_or("bits").alias("bits"))


def filter_left(a_new: DataFrame, r: DataFrame, ell: int = 64, trans: bool = False, cells: int = BROADCAST_CELLS) -> DataFrame:
    """A^R: cells of the rows in R whose inner index has its bit set."""
    row, inner = ("j", "i") if trans else ("i", "j")
    rb = r.select(F.col("i").alias(row), F.col("bits").alias("_r"))
    rb = F.broadcast(rb) if fits(rb, cells) else rb
    return a_new.join(rb, row).where(F.col("_r").bitwiseAND(bit_of(F.col(inner), ell)) != 0).select("i", "j", "v")


def filter_right(b_new: DataFrame, r: DataFrame, ell: int = 64, trans: bool = False, cells: int = BROADCAST_CELLS) -> DataFrame:
    """The mirror: cells of B' in the result columns of R(j, bits) whose inner index has its bit set."""
    col, inner = ("i", "j") if trans else ("j", "i")
    rb = r.select(F.col("j").alias(col), F.col("bits").alias("_r"))
    rb = F.broadcast(rb) if fits(rb, cells) else rb
    return b_new.join(rb, col).where(F.col("_r").bitwiseAND(bit_of(F.col(inner), ell)) != 0).select("i", "j", "v")


def exact_left(a_new: DataFrame, b_new: DataFrame, c_star: DataFrame, trans=(False, False)) -> DataFrame:
    """Cells of A' that some changed cell truly needs: the oracle of the fingerprints."""
    left, right = sides(a_new, b_new, trans)
    used = left.select("i", "k").join(right.select("k", "j"), "k").join(c_star.select("i", "j"), ["i", "j"], "left_semi").select("i", "k").distinct()
    row, inner = ("j", "i") if trans[0] else ("i", "j")
    return a_new.join(used.select(F.col("i").alias(row), F.col("k").alias(inner)), ["i", "j"], "left_semi")


def masked_with_bits(a_r: DataFrame, b_new: DataFrame, c_star: DataFrame, s: Semiring, ell: int = 64, trans=(False, False)) -> DataFrame:
    """(i, j, v, bits) of A^R·B' at C*; the mask is tested before values are accumulated."""
    left, right = sides(a_r, b_new, trans)
    return with_bits(sized(left).join(right, "k").join(sized(c_star.select("i", "j")), ["i", "j"], "left_semi"), s, ell)


def replace_in_mask(c: DataFrame, z: DataFrame, c_star: DataFrame) -> DataFrame:
    """C with its cells at C* replaced by Z; cells of C* without a term in Z vanish."""
    kept = c.join(sized(c_star.select("i", "j")), ["i", "j"], "left_anti")
    return kept.unionByName(z.select(*c.columns))


@dataclass
class Steps:
    """What one general update went through, for measures and tests."""

    pattern: DataFrame
    needed: DataFrame
    rows: DataFrame
    filtered: DataFrame
    z: DataFrame
    result: DataFrame


def maintain_general(c: DataFrame, a_old: DataFrame, a_new: DataFrame, a_star: DataFrame | None, b_new: DataFrame, b_star: DataFrame | None, s: Semiring, *, ell: int = 64, variant: str = "bits", side: str = "left", trans=(False, False)) -> Steps:
    """C(i, j, v, bits) after a batch; a_star and b_star hold the changed cells' structure (i, j).

    variant: bits (fingerprint of the inner index), rows (the bits decide about whole rows only),
    none (all rows of C*), exact (the true inner indices). side: which operand is filtered.
    C*, the rows' bits and the filtered operand are counted before they are sent, and used again:
    they are written once. C itself is only scanned where they are small.
    """
    c_star = materialize(compute_pattern(a_old, a_star, b_new, b_star, ell, trans), "pattern")
    e = needed_bits(c, c_star)
    r = rows_needed(c, c_star, "i" if side == "left" else "j")
    if variant in ("bits", "rows"):  # the others do not read the stored product
        r = materialize(r, "rows")
    a_r, b_r = a_new, b_new
    if variant == "bits" and side == "left":
        a_r = filter_left(a_new, r, ell, trans[0])
    elif variant == "bits":
        b_r = filter_right(b_new, r, ell, trans[1])
    elif variant == "exact":
        a_r = exact_left(a_new, b_new, c_star, trans)
    else:
        row = "j" if trans[0] else "i"
        touched = r.where("bits <> 0") if variant == "rows" else c_star.select("i").distinct()
        a_r = a_new.join(touched.select(F.col("i").alias(row)), row, "left_semi").select("i", "j", "v")
    if side == "left":
        a_r = materialize(a_r, "filtered")
    z = masked_with_bits(a_r, b_r, c_star, s, ell, trans)
    return Steps(c_star, e, r, a_r if side == "left" else b_r, z, replace_in_mask(c, z, c_star))
