"""Products kept correct under changes that are additions in the semiring.

new = old ⊕ delta, so the result changes by A*·B' ⊕ A·B*: only deltas and what they produce move.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamat.functions.semiring import PLUS_TIMES, Semiring
from deltamat.operators.layout import Grid
from deltamat.operators.matrix import ewise_add
from deltamat.operators.multiply import BROADCAST_CELLS, fits, folded, sides

FORMS = ("two_term", "mirrored", "expanded")


def pairs(a: DataFrame, b: DataFrame, small: str, trans: tuple[bool, bool], cells: int) -> DataFrame:
    """Joined terms (i, j, k, av, bv) with the named side broadcast where it is checked to be small enough."""
    left, right = sides(a, b, trans)
    if small == "left":
        left = F.broadcast(left) if fits(left, cells) else left.hint("shuffle_hash")
    else:
        right = F.broadcast(right) if fits(right, cells) else right.hint("shuffle_hash")
    return left.join(right, "k").select("i", "j", "k", "av", "bv")


def delta_terms(a_old: DataFrame, a_star: DataFrame | None, b_old: DataFrame, b_star: DataFrame | None, a_new: DataFrame | None, b_new: DataFrame | None, form: str, trans: tuple[bool, bool], cells: int) -> DataFrame:
    """The joined terms whose ⊕ is the change of the product; None: that operand is static."""
    out = []
    if form == "two_term":
        if a_star is not None:
            out.append(pairs(a_star, b_new if b_star is not None else b_old, "left", trans, cells))
        if b_star is not None:
            out.append(pairs(a_old, b_star, "right", trans, cells))
    elif form == "mirrored":
        if a_star is not None:
            out.append(pairs(a_star, b_old, "left", trans, cells))
        if b_star is not None:
            out.append(pairs(a_new if a_star is not None else a_old, b_star, "right", trans, cells))
    elif form == "expanded":
        if a_star is not None:
            out.append(pairs(a_star, b_old, "left", trans, cells))
        if b_star is not None:
            out.append(pairs(a_old, b_star, "right", trans, cells))
        if a_star is not None and b_star is not None:
            out.append(pairs(a_star, b_star, "left", trans, cells))
    else:
        raise ValueError(form)
    if not out:
        raise ValueError("no operand changes")
    terms = out[0]
    for t in out[1:]:
        terms = terms.unionByName(t)
    return terms


def delta_product(a_old, a_star, b_old, b_star, s: Semiring = PLUS_TIMES, *, a_new=None, b_new=None, form: str = "two_term", trans=(False, False), cells: int = BROADCAST_CELLS) -> DataFrame:
    """C*, with one aggregate (and one exchange, of partial results only) over all terms.

    Where a form needs a new operand that is not given, it is old ⊕ delta.
    """
    if b_star is not None and b_new is None and form == "two_term":
        b_new = ewise_add(b_old, b_star, s)
    if a_star is not None and a_new is None and form == "mirrored":
        a_new = ewise_add(a_old, a_star, s)
    return folded(delta_terms(a_old, a_star, b_old, b_star, a_new, b_new, form, trans, cells), s)


def maintain(c: DataFrame, c_star: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    """C' = C ⊕ C*."""
    return ewise_add(c, c_star, s)


def simulate_rounds(a: DataFrame, a_star: DataFrame, b_new: DataFrame, b_star: DataFrame, ga: Grid, gb: Grid, s: Semiring = PLUS_TIMES) -> tuple[DataFrame, DataFrame]:
    """(C*, volume): the grid's rounds as tags on cells, for validation and counting.

    Terms are made by the process that holds the large operand's block and belong to the process of
    the result's block; a partial is what one producer sums up for one result cell. volume lists
    off-diagonal deltas (sent across the diagonal first), copies along rows or columns, and partials
    whose producer is not their owner.
    """
    q = ga.qr
    rows = lambda c: ga.bi(F.col(c))
    inner_a, inner_b, cols = (lambda c: ga.bj(F.col(c))), (lambda c: gb.bi(F.col(c))), (lambda c: gb.bj(F.col(c)))
    left, right = sides(a_star, b_new)
    x = left.join(right, "k").select("i", "j", s.times(F.col("av"), F.col("bv")).alias("v"), inner_b("k").alias("pi"), cols("j").alias("pj"))
    left, right = sides(a, b_star)
    y = left.join(right, "k").select("i", "j", s.times(F.col("av"), F.col("bv")).alias("v"), rows("i").alias("pi"), inner_a("k").alias("pj"))
    tagged = x.withColumn("term", F.lit("x")).unionByName(y.withColumn("term", F.lit("y")))
    partial = tagged.groupBy("term", "pi", "pj", "i", "j").agg(s.plus_agg(F.col("v")).alias("v"))
    partial = partial.withColumns({"oi": rows("i"), "oj": cols("j")})
    c_star = partial.groupBy("i", "j").agg(s.plus_agg(F.col("v")).alias("v"))
    sent = a_star.where(rows("i") != inner_a("j")).agg(F.count("*").alias("n")).unionByName(b_star.where(inner_b("i") != cols("j")).agg(F.count("*").alias("n"))).agg(F.sum("n").alias("cells")).select(F.lit("transposed_send").alias("step"), "cells")
    copies = a_star.agg(F.count("*").alias("n")).unionByName(b_star.agg(F.count("*").alias("n"))).agg((F.sum("n") * (q - 1)).alias("cells")).select(F.lit("broadcast").alias("step"), "cells")
    moved = partial.agg(F.count_if((F.col("pi") != F.col("oi")) | (F.col("pj") != F.col("oj"))).alias("cells")).select(F.lit("reduce").alias("step"), "cells")
    return c_star, sent.unionByName(copies).unionByName(moved)
