"""Semirings as pairs of column expressions, each with the SQL text that an oracle can use."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import product
from typing import Any

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """plus_agg folds a group, plus and times combine two values; zero is never stored.

    minus is there for rings only; times_commutative tells whether a product may be turned round;
    idempotent declares a ⊕ a = a, which closures rely on and check_laws() tests. distributive is
    false where ⊗ looks at structure only: a change of a stored value is then no addition.
    """

    name: str
    plus_agg: Callable[[Column], Column]
    plus: Callable[[Column, Column], Column]
    times: Callable[[Column, Column], Column]
    zero: Any
    one: Any = None
    minus: Callable[[Column, Column], Column] | None = None
    times_commutative: bool = True
    sql_plus: str = ""
    sql_times: str = ""
    py_plus: Callable[[Any, Any], Any] | None = None
    py_times: Callable[[Any, Any], Any] | None = None
    idempotent: bool = False
    distributive: bool = True

    @property
    def is_ring(self) -> bool:
        return self.minus is not None

    @staticmethod
    def define(name, plus_agg, plus, times, zero, one=None, minus=None, **more) -> Semiring:
        return Semiring(name, plus_agg, plus, times, zero, one, minus, **more)


_add = lambda a, b: a + b
_mul = lambda a, b: a * b
INF = float("inf")

PLUS_TIMES = Semiring("plus_times", F.sum, _add, _mul, 0, 1, lambda a, b: a - b, True, "sum({})", "({}) * ({})", _add, _mul)
MIN_PLUS = Semiring("min_plus", F.min, F.least, _add, INF, 0, None, True, "min({})", "({}) + ({})", min, _add, True)
MAX_PLUS = Semiring("max_plus", F.max, F.greatest, _add, -INF, 0, None, True, "max({})", "({}) + ({})", max, _add, True)
MAX_MIN = Semiring("max_min", F.max, F.greatest, F.least, -INF, INF, None, True, "max({})", "least({}, {})", max, min, True)
MIN_MAX = Semiring("min_max", F.min, F.least, F.greatest, INF, -INF, None, True, "min({})", "greatest({}, {})", min, max, True)
MAX_TIMES = Semiring("max_times", F.max, F.greatest, _mul, 0, 1, None, True, "max({})", "({}) * ({})", max, _mul, True)
OR_AND = Semiring("or_and", F.bool_or, lambda a, b: a | b, lambda a, b: a & b, False, True, None, True, "bool_or({})", "({}) AND ({})", lambda a, b: a or b, lambda a, b: a and b, True)
PATTERN = Semiring("any_pair", F.max, F.greatest, lambda a, b: F.lit(1).cast("long"), 0, 1, None, True, "max({})", "CASE WHEN ({}) IS NOT NULL AND ({}) IS NOT NULL THEN 1 END", max, lambda a, b: 1, True)
COUNT_PAIR = Semiring("plus_pair", F.sum, _add, lambda a, b: F.lit(1).cast("long"), 0, 1, None, True, "sum({})", "CASE WHEN ({}) IS NOT NULL AND ({}) IS NOT NULL THEN 1 END", _add, lambda a, b: 1, distributive=False)

ALL = {s.name: s for s in (PLUS_TIMES, MIN_PLUS, MAX_PLUS, MAX_MIN, MIN_MAX, MAX_TIMES, OR_AND, PATTERN, COUNT_PAIR)}


def bit_of(k: Column, ell: int = 64) -> Column:
    """The fingerprint bit of inner index k among ell bits; bit 63 makes the number negative."""
    return F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(k, F.lit(ell)).cast("int"))


def bit_or(ell: int = 64) -> Semiring:
    """The collector of inner indices: ⊕ is bitwise or; times is given the bit itself."""
    return Semiring(f"bit_or_{ell}", F.bit_or, lambda a, b: a.bitwiseOR(b), lambda a, b: a.bitwiseAND(b), 0, -1, None, True, "bit_or({})", "({}) & ({})", lambda a, b: a | b, lambda a, b: a & b, True)


def check_laws(s: Semiring, samples: list, close: Callable[[Any, Any], bool] = lambda a, b: a == b) -> dict[str, bool]:
    """Which laws hold on all triples of the samples: the driver's loop is over a handful of values."""
    p, t, z = s.py_plus, s.py_times, s.zero
    triples = list(product(samples, repeat=3))
    laws = {
        "plus_associative": all(close(p(p(a, b), c), p(a, p(b, c))) for a, b, c in triples),
        "plus_commutative": all(close(p(a, b), p(b, a)) for a, b, _ in triples),
        "times_associative": all(close(t(t(a, b), c), t(a, t(b, c))) for a, b, c in triples),
        "distributive": all(close(t(a, p(b, c)), p(t(a, b), t(a, c))) and close(t(p(a, b), c), p(t(a, c), t(b, c))) for a, b, c in triples),
        "neutral": all(close(p(a, z), a) for a in samples),
        "annihilates": all(close(t(a, z), z) and close(t(z, a), z) for a in samples),
    }
    if s.idempotent:
        laws["idempotent"] = all(close(p(a, a), a) for a in samples)
    if s.one is not None:
        laws["one"] = all(close(t(a, s.one), a) and close(t(s.one, a), a) for a in samples)
    return laws
