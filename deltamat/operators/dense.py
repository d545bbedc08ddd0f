"""Sums of products whose result is nearly full: rows times a dense right operand.

Where many inner indices meet in every cell, joined terms outnumber the result many times over. If
both operands are checked to be small, every task holds them and makes its own rows of the result,
with nothing exchanged. Anything else is refused with None, and the caller joins terms.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from deltamat.operators.multiply import BROADCAST_CELLS, fits, sides
from deltamat.operators.walks import run_blocks

#: Entries of the right operand as a full array; multiplications a term below which rows pay.
ENTRIES, WORTH = 4 << 20, 64


@dataclass(frozen=True)
class Operands:
    """Rows of the left operand as (row, inner, value) in order of rows; the right one inner × ids, full."""

    row_ids: np.ndarray
    at: np.ndarray
    inner: np.ndarray
    values: np.ndarray
    ids: np.ndarray
    right: np.ndarray
    bit: np.ndarray

    def left(self, part: np.ndarray) -> np.ndarray:
        out = np.zeros((len(part), len(self.right)))
        where = np.searchsorted(self.row_ids, part)
        for n, r in enumerate(where):
            cut = slice(self.at[r], self.at[r + 1])
            np.add.at(out[n], self.inner[cut], self.values[cut])
        return out


def _arrays(df: DataFrame, names: tuple[str, ...], cells: int) -> list[np.ndarray] | None:
    """Columns as arrays, or None beyond ``cells`` rows, for nulls and for values that are not above 0."""
    if not fits(df, cells):
        return None
    t = df.select(*[F.col(n).cast("long").alias(n) for n in names]).toArrow()
    if any(c.null_count for c in t.columns):
        return None
    out = [c.to_numpy() for c in t.columns]
    return out if not len(out[2]) or out[2].min() > 0 else None


def operands(left: DataFrame, right: DataFrame, ell: int, cells: int) -> Operands | None:
    if not all(isinstance(df.schema[c].dataType, LongType) for df, c in ((left, "av"), (right, "bv"))):
        return None
    x, y = _arrays(left, ("i", "k", "av"), cells), _arrays(right, ("k", "j", "bv"), cells)
    if x is None or y is None:
        return None
    (i, k, av), (bk, j, bv) = x, y
    inner, ids = np.intersect1d(k, bk), np.unique(j)
    if not len(inner) or len(inner) * len(ids) > ENTRIES:
        return None
    mine, theirs = np.isin(k, inner), np.isin(bk, inner)
    i, k, av = i[mine], np.searchsorted(inner, k[mine]), av[mine]
    bk, j, bv = np.searchsorted(inner, bk[theirs]), j[theirs], bv[theirs]
    row_ids = np.unique(i)
    terms = float(np.bincount(k, minlength=len(inner)) @ np.bincount(bk, minlength=len(inner)))
    if terms * WORTH < float(len(row_ids)) * len(inner) * len(ids):
        return None
    order = np.argsort(i, kind="stable")
    i, k, av = i[order], k[order], av[order]
    b = np.zeros((len(inner), len(ids)))
    np.add.at(b, (bk, np.searchsorted(ids, j)), bv)
    at = np.append(np.searchsorted(i, row_ids), len(i))
    # Sums in doubles are exact below 2**53.
    if float(np.add.reduceat(av.astype(float), at[:-1]).max()) * float(b.max()) >= 2.0**52:
        return None
    return Operands(row_ids, at, k, av, ids, b, np.mod(inner, ell))


def product_rows(upper: bool, bits: bool):
    def rows(o: Operands, part: np.ndarray):
        a = o.left(part)
        c = a @ o.right
        if upper:
            c[part[:, None] >= o.ids[None, :]] = 0
        s, j = np.nonzero(c)
        out = [s, o.ids[j], c[s, j].astype(np.int64)]
        if bits:
            marks = np.zeros(c.shape, np.uint64)
            some_a, some_b = (a > 0).astype(np.float32), (o.right > 0).astype(np.float32)
            for n in np.unique(o.bit):
                of = np.flatnonzero(o.bit == n)
                marks |= (some_a[:, of] @ some_b[of] > 0).astype(np.uint64) << np.uint64(n)
            out.append(marks[s, j].view(np.int64))
        yield tuple(out)

    return rows


def dense_product(a: DataFrame, b: DataFrame, trans: tuple[bool, bool] = (False, False), *, upper: bool = False, bits: bool = False, ell: int = 64, cells: int = BROADCAST_CELLS) -> DataFrame | None:
    """A·B over (+, ·) as (i, j, v), with fingerprints if asked for; upper: cells with i < j only."""
    left, right = sides(a, b, trans)
    o = operands(left, right, ell, cells)
    if o is None:
        return None
    sources = left.join(right.select("k").distinct(), "k", "left_semi").select("i")
    return run_blocks(sources, o, product_rows(upper, bits), "i long, j long, v long" + (", bits long" if bits else ""), 40)
