"""What the dynamic methods are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame

from deltamat.functions.semiring import PLUS_TIMES, Semiring
from deltamat.operators.layout import Grid, assign_grid, to_dcsr
from deltamat.operators.matrix import ewise_add
from deltamat.operators.multiply import spgemm, spgemm_generic, spgemm_grid, spgemm_rowpart
from deltamat.operators.updates import redistribute


def recompute(a_new: DataFrame, b_new: DataFrame, s: Semiring = PLUS_TIMES, grids: tuple[Grid, Grid] | None = None) -> DataFrame:
    """The full product of the changed operands, by the static grid or by a plain join."""
    return spgemm_grid(a_new, b_new, *grids, s) if grids else spgemm(a_new, b_new, s)


def delta_static(c: DataFrame, a_star: DataFrame, b: DataFrame, grids: tuple[Grid, Grid], s: Semiring = PLUS_TIMES) -> DataFrame:
    """A*·B by the static grid, which copies all of B, then the addition."""
    return ewise_add(c, spgemm_grid(a_star, b, *grids, s), s)


def sorted_redistribution(star: DataFrame, g: Grid) -> DataFrame:
    return redistribute(star, g, "sort")


def static_dcsr(cells: DataFrame, g: Grid) -> DataFrame:
    """Static packed rows built from redistributed cells."""
    return to_dcsr(redistribute(cells, g).select("i", "j", "v"), g)


generic_contract = spgemm_generic
row_partitioned = spgemm_rowpart


def unpermuted(m: DataFrame, n: int, k: int, q: int) -> DataFrame:
    return assign_grid(m, Grid(n, k, q))
