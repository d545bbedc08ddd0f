"""The experiments, on the given tables: what is timed, against which contender, at which sizes.

Every function returns rows as dictionaries; ``python -m deltamat.workloads SF_DIR [NAME...]`` prints
them. Reading, the initial half and static operands are written before the clock starts, and all
contenders get the same draws.
"""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.functions import semiring as sr
from deltamat.operators import baselines, layout, matrix, multiply, updates
from deltamat.operators import dynamic_algebraic as alg
from deltamat.operators import dynamic_general as gen
from deltamat.operators.layout import Affine, Grid
from deltamat.plans import cost
from deltamat.queries.base import MAKE
from deltamat.sources import instances as inst
from deltamat.sources.scratch import discard, materialize, new_path
from deltamat.sources.store import DeltaStore, MatrixStore, StaticStore

FRACTIONS = (0.001, 0.005, 0.01, 0.05)
BATCHES = 10
_ORDER, _PART, _SUPP, _CUST, _USER = ("orders", "o_orderkey"), ("part", "p_partkey"), ("supplier", "s_suppkey"), ("customer", "c_custkey"), ("events", "user_id")
KEYS = {"order_part": (_ORDER, _PART), "part_supp": (_PART, _SUPP), "part_order": (_PART, _ORDER), "supp_order": (_SUPP, _ORDER), "order_cust": (_ORDER, _CUST), "user_succ": (_USER, _USER)}


def run_all(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def timed(f: Callable[[], object]) -> float:
    began = time.perf_counter()
    f()
    return time.perf_counter() - began


def drawn(spark, d, name: str) -> DataFrame:
    return materialize(inst.draw(MAKE[name](spark, d), 7), name)


def grid(spark, d, name: str, q: int = 4, permuted: bool = True) -> Grid:
    n, m = inst.dims(spark, d, *KEYS[name])
    return Grid(n, m, q, None, _affine(n) if permuted else None, _affine(m) if permuted else None)


def _affine(n: int) -> Affine:
    from math import gcd

    return Affine(n, next(a for a in range(7919, 7919 + n + 2) if gcd(a, n) == 1))


def construction(spark, d, names=tuple(KEYS)) -> list[dict]:
    """Dynamic blocks against sorted redistribution and static packed rows."""
    rows = []
    for name in names:
        m, g = drawn(spark, d, name).select("i", "j", "v"), grid(spark, d, name)
        ways = {"dynamic": lambda m=m, g=g: MatrixStore.create(m, new_path(spark, "w"), g), "static_sorted": lambda m=m, g=g: run_all(baselines.sorted_redistribution(m, g)), "static_dcsr": lambda m=m, g=g: run_all(baselines.static_dcsr(m, g))}
        rows += [{"instance": name, "contender": w, "seconds": timed(f)} for w, f in ways.items()]
    return rows


def _stores(spark, d, name: str, batch: Callable[[DataFrame, float, int], DataFrame], start: str, fractions, batches: int) -> list[dict]:
    m, g, rows = drawn(spark, d, name), grid(spark, d, name), []
    for fraction in fractions:
        for kind in (DeltaStore, MatrixStore, StaticStore):
            s = kind.create(m.where(start).select("i", "j", "v"), new_path(spark, "w"), g)
            for k in range(batches):
                u = materialize(batch(m, fraction, k), "batch")
                seconds = timed(lambda s=s, u=u, k=k: s.apply(updates.UpdateBatch.build(u, k)))
                rows.append({"instance": name, "fraction": fraction, "contender": kind.__name__, "batch": k, "seconds": seconds, "per_cell": seconds / max(1, u.count())})
    return rows


def _slice(m: DataFrame, lo: int, fraction: float, k: int) -> DataFrame:
    w = int(fraction * inst.PARTS)
    return m.where((F.col("u") >= lo + k * w) & (F.col("u") < lo + (k + 1) * w))


def insertion(spark, d, name="order_part", fractions=FRACTIONS, batches=BATCHES) -> list[dict]:
    """Half is there, batches come from the other half."""
    return _stores(spark, d, name, lambda m, f, k: _slice(m, 500_000, f, k).select("i", "j", "v", F.lit("set").alias("op")), "u < 500000", fractions, batches)


def value_updates(spark, d, name="order_part", fractions=FRACTIONS, batches=BATCHES) -> list[dict]:
    return _stores(spark, d, name, lambda m, f, k: _slice(m, 0, f, k).select("i", "j", (F.col("v") + 1).alias("v"), F.lit("set").alias("op")), "true", fractions, batches)


def deletion(spark, d, name="order_part", fractions=FRACTIONS, batches=BATCHES) -> list[dict]:
    return _stores(spark, d, name, lambda m, f, k: _slice(m, 0, f, k).select("i", "j", "v", F.lit("del").alias("op")), "true", fractions, batches)


def scaling_insert(spark, d, name="order_part", processes=(4, 16, 64), per_process: int = 2000, batches: int = 3) -> list[dict]:
    """Virtual processes: each of several batches grows with p; cells moved, and seconds by step.

    first and second are the two exchanges, sort the order within a block, insert the appended blocks.
    """
    m, rows = drawn(spark, d, name), []
    total = m.count()
    for p in processes:
        q = round(p**0.5)
        g = grid(spark, d, name, q)
        s = DeltaStore.create(m.where("u < 500000").select("i", "j", "v"), new_path(spark, "w"), g)
        for k in range(batches):
            share = min(0.5 / batches, per_process * p / total)
            u = materialize(_slice(m, 500_000, share, k).select("i", "j", "v"), "batch")
            trace = materialize(updates.redistribute(u, g, "two_step"), "trace")
            moved = {r.step: r.moved for r in cost.redistribution(trace).collect()}
            laid = materialize(updates.redistribute(u, g, "one_step"), "laid")
            n, steps = u.count(), {
                "first": lambda trace=trace: run_all(trace.repartition("mid")),
                "second": lambda trace=trace: run_all(trace.repartition("dst")),
                "sort": lambda laid=laid: run_all(laid.sortWithinPartitions("bi", "bj", "i", "j")),
                "insert": lambda s=s, u=u, k=k: s.apply(updates.UpdateBatch.build(u.withColumn("op", F.lit("set")), k)),
            }
            seconds = {name_: timed(f) for name_, f in steps.items()}
            rows.append({"p": p, "batch": k, "cells": n, **seconds, "per_cell": sum(seconds.values()) / max(1, n), **{f"moved_{k_}": v for k_, v in moved.items()}})
    return rows


def rmat(spark, d, scale: int = 16, edges: int = 1 << 18, parts: int = 4, processes=(4, 16, 64), weak: bool = False) -> list[dict]:
    """Insertions of a generated power-law graph in batches, for each number of virtual processes.

    Strong: the same edges for every p. weak: ``edges`` for each process, so the graph grows with p.
    The blocks' balance is told with and without the permutation.
    """
    rows, n = [], 1 << scale
    perm = Affine(n)
    for p in processes:
        q, total = round(p**0.5), edges * (p if weak else 1)
        e = materialize(inst.rmat(spark, scale, total), "edges")
        s = DeltaStore.create(matrix.empty(spark), new_path(spark, "w"), Grid(n, n, q, None, perm, perm))
        for k in range(parts):
            part = e.where(F.pmod("e", F.lit(parts)) == k).groupBy("i", "j").agg(F.count("*").alias("v"))
            u = materialize(part.withColumn("op", F.lit("add")), "batch")
            seconds = timed(lambda u=u, k=k: s.apply(updates.UpdateBatch.build(u, k)))
            rows.append({"p": p, "edges": total, "batch": k, "seconds": seconds, "per_cell": seconds * parts / total})
        cells = e.groupBy("i", "j").agg(F.count("*").alias("v"))
        for name, x in (("permuted", perm), ("plain", None)):
            rows.append({"p": p, "balance": name, "ratio": cost.balance(cells, n, n, q, x, x).first().ratio})
        discard(e)
    return rows


def rmat_weak(spark, d, scale: int = 16, edges: int = 1 << 14, parts: int = 2, processes=(4, 16)) -> list[dict]:
    return rmat(spark, d, scale, edges, parts, processes, weak=True)


def dynamic_product(spark, d, left="order_part", right="part_supp", fractions=FRACTIONS, batches: int = BATCHES, contenders=("delta", "delta_static", "recompute", "generic", "rowpart")) -> list[dict]:
    """(+, ·): the left operand starts empty and takes ten batches, the right one is there in full.

    A method's time covers the new left operand, the product's change and its addition to the product;
    the contenders that know no change make the product of the new operands.
    """
    m, b = drawn(spark, d, left), materialize(MAKE[right](spark, d), right)
    n, k, c = *inst.dims(spark, d, *KEYS[left]), inst.dims(spark, d, KEYS[right][1])[0]
    grids, rows = (Grid(n, k, 2), Grid(k, c, 2)), []
    for f in fractions:
        a = materialize(matrix.empty(spark), "a")
        held = {w: materialize(multiply.spgemm(a, b), "c") for w in ("delta", "delta_static")}
        for t in range(batches):
            star = materialize(_slice(m, 0, f, t).select("i", "j", "v"), "star")
            new = materialize(updates.apply_add(a, star), "new")
            cells, after = star.count(), {}

            def kept(w, change, after=after, held=held):
                after[w] = materialize(alg.maintain(held[w], change), "c")

            ways = {
                "delta": lambda a=a, star=star, kept=kept: kept("delta", alg.delta_product(a, star, b, None)),
                "delta_static": lambda star=star, kept=kept: kept("delta_static", multiply.spgemm_grid(star, b, *grids)),
                "recompute": lambda new=new: materialize(multiply.spgemm_grid(new, b, *grids), "c"),
                "generic": lambda new=new: materialize(multiply.spgemm_generic(new, b), "c"),
                "rowpart": lambda new=new: materialize(multiply.spgemm_rowpart(new, b, 8), "c"),
            }
            insert = timed(lambda a=a, star=star: run_all(updates.apply_add(a, star)))
            for w in contenders:
                seconds = insert + timed(ways[w])
                rows.append({"fraction": f, "batch": t, "contender": w, "seconds": seconds, "per_cell": seconds / max(1, cells)})
            discard(a, *(held[w] for w in after))
            held, a = held | after, new
    return rows


def product_breakdown(spark, d, left="order_part", right="part_supp", processes=(4, 16, 64), per_process: int = 100) -> list[dict]:
    """Seconds and cells of each step of a delta product on virtual processes, as the batch grows with p."""
    m, b, rows = drawn(spark, d, left), materialize(MAKE[right](spark, d), right), []
    n, k, c = *inst.dims(spark, d, *KEYS[left]), inst.dims(spark, d, KEYS[right][1])[0]
    old = materialize(m.where("u < 500000").select("i", "j", "v"), "old")
    product, total = materialize(multiply.spgemm(old, b), "c"), m.count()
    for p in processes:
        q = round(p**0.5)
        ga = Grid(n, k, q, None, _affine(n), _affine(k))
        gb = Grid(k, c, q, None, _affine(k), _affine(c))
        star = materialize(_slice(m, 500_000, min(0.5, per_process * p / total), 0).select("i", "j", "v"), "star")
        laid = star.withColumns({"bi": ga.bi(F.col("i")), "bj": ga.bj(F.col("j"))})
        across = laid.where("bi <> bj").repartition("bj", "bi")
        copied = laid.withColumn("to", F.explode(F.sequence(F.lit(0), F.lit(q - 1)))).repartition("bj", "to")
        terms = alg.pairs(star, b, "left", (False, False), multiply.BROADCAST_CELLS)
        c_star = materialize(multiply.folded(terms, sr.PLUS_TIMES), "c_star")
        moved = {r.step: r.cells for r in alg.simulate_rounds(old, star, b, matrix.empty(spark), ga, gb)[1].collect()}
        steps = {
            "send": lambda across=across: run_all(across),
            "broadcast": lambda copied=copied: run_all(copied),
            "multiply": lambda terms=terms: run_all(terms),
            "multiply_reduce": lambda terms=terms: run_all(multiply.folded(terms, sr.PLUS_TIMES)),
            "add": lambda c_star=c_star: run_all(alg.maintain(product, c_star)),
        }
        rows.append({"p": p, "cells": star.count(), **{name: timed(f) for name, f in steps.items()}, **{f"cells_{k_}": v for k_, v in moved.items()}})
    return rows


def general_product(spark, d, left="part_order", right="order_cust", fractions=FRACTIONS, batches: int = BATCHES, contenders=("masked", "recompute", "generic")) -> list[dict]:
    """(min, +) with deletions, raises and insertions in every batch: the masked product against recomputation."""
    m, b = drawn(spark, d, left), materialize(MAKE[right](spark, d), right)
    rows = []
    for f in fractions:
        t = int(f * inst.PARTS / 3)
        a = materialize(m.where("u < 500000").select("i", "j", "v"), "a")
        c = materialize(gen.product_with_bits(a, b, sr.MIN_PLUS), "c")
        for k in range(batches):
            lo, up = k * 2 * t, 500_000 + k * t
            star = materialize(m.where(f"u >= {lo} and u < {lo + 2 * t} or u >= {up} and u < {up + t}").select("i", "j"), "star")
            gone, raised = m.where(f"u >= {lo} and u < {lo + t}").select("i", "j"), m.where(f"u >= {lo + t} and u < {lo + 2 * t}").select("i", "j", F.lit(100).cast("long").alias("more"))
            kept = a.join(gone, ["i", "j"], "left_anti").join(raised, ["i", "j"], "left").select("i", "j", (F.col("v") + F.coalesce("more", F.lit(0))).alias("v"))
            new = materialize(kept.unionByName(m.where(f"u >= {up} and u < {up + t}").select("i", "j", "v")), "new")
            after = []
            ways = {
                "masked": lambda a=a, new=new, star=star, c=c, after=after: after.append(materialize(gen.maintain_general(c, a, new, star, b, None, sr.MIN_PLUS).result, "c")),
                "recompute": lambda new=new: materialize(multiply.spgemm(new, b, sr.MIN_PLUS), "c"),
                "generic": lambda new=new: materialize(multiply.spgemm_generic(new, b, sr.MIN_PLUS), "c"),
            }
            cells = star.count()
            for w in contenders:
                seconds = timed(ways[w])
                rows.append({"fraction": f, "batch": k, "contender": w, "seconds": seconds, "per_cell": seconds / max(1, cells)})
            if after:
                discard(a, c)
                a, c = new, after[0]
    return rows


def scaling_product(spark, d, left="order_part", right="part_supp", processes=(4, 16, 64), per_process: int = 100) -> list[dict]:
    """Cells moved by each step of the delta product as the batch grows with p."""
    m, b, rows = drawn(spark, d, left), materialize(MAKE[right](spark, d), right), []
    n, k, c = *inst.dims(spark, d, *KEYS[left]), inst.dims(spark, d, KEYS[right][1])[0]
    total = m.count()
    for p in processes:
        q = round(p**0.5)
        star = materialize(_slice(m, 500_000, min(0.5, per_process * p / total), 0).select("i", "j", "v"), "star")
        ga, gb = Grid(n, k, q, None, _affine(n), _affine(k)), Grid(k, c, q, None, _affine(k), _affine(c))
        c_star, volume = alg.simulate_rounds(m, star, b, matrix.empty(spark), ga, gb)
        seconds = timed(lambda star=star: run_all(alg.delta_product(m, star, b, None)))
        rows.append({"p": p, "cells": star.count(), "seconds": seconds, "c_star": c_star.count(), **{r.step: r.cells for r in volume.collect()}})
    return rows


def crossover(spark, d, parts=(1000, 10_000, 100_000, 500_000)) -> list[dict]:
    from deltamat.queries.measures import volumes

    return [volumes(spark, d, p).first().asDict() for p in parts]


def filter_ablation(spark, d, left="part_order", right="order_cust", ells=(8, 16, 32, 62, 64), fraction: float = 0.01) -> list[dict]:
    """Cells of the left operand that each width of fingerprint leaves, against rows only and exact."""
    m, b, rows = drawn(spark, d, left), materialize(MAKE[right](spark, d), right), []
    t = int(fraction * inst.PARTS / 3)
    old = materialize(m.where("u < 500000").select("i", "j", "v"), "old")
    new = materialize(m.where(f"u >= {t} and u < {500_000 + t}").select("i", "j", "v"), "new")
    star = materialize(m.where(f"u < {2 * t} or u >= 500000 and u < {500_000 + t}").select("i", "j"), "star")
    for ell in ells:
        c = materialize(gen.product_with_bits(old, b, sr.MIN_PLUS, ell), "c")
        s = gen.maintain_general(c, old, new, star, b, None, sr.MIN_PLUS, ell=ell)
        rows.append({"ell": ell, **cost.filter_effect(new, b, s.pattern, s.rows, ell).first().asDict()})
    return rows


def both_sides(spark, d, left="order_part", right="part_supp", fraction: float = 0.01) -> list[dict]:
    a, b = drawn(spark, d, left), drawn(spark, d, right)
    half = lambda m: materialize(m.where("u < 500000").select("i", "j", "v"), "half")
    a0, b0 = half(a), half(b)
    sa, sb = (materialize(_slice(m, 500_000, fraction, 0).select("i", "j", "v"), "star") for m in (a, b))
    return [{"form": f, "seconds": timed(lambda f=f: run_all(alg.delta_product(a0, sa, b0, sb, form=f)))} for f in alg.FORMS]


def balance(spark, d, name="order_part") -> list[dict]:
    m = drawn(spark, d, name)
    n, k = inst.dims(spark, d, *KEYS[name])
    return [{"permutation": p, "ratio": cost.balance(m, n, k, 4, *((_affine(n), _affine(k)) if p else (None, None))).first().ratio} for p in (True, False)]


def threads(spark, d, name="order_part", t: int = 6) -> list[dict]:
    return [r.asDict() for r in layout.thread_buckets(drawn(spark, d, name), t).collect()]


ALL = {f.__name__: f for f in (construction, insertion, value_updates, deletion, scaling_insert, rmat, rmat_weak, dynamic_product, product_breakdown, general_product, scaling_product, crossover, filter_ablation, both_sides, balance, threads)}


def main(args: list[str]) -> None:
    spark = SparkSession.builder.getOrCreate()
    for name in args[1:] or ALL:
        for row in ALL[name](spark, args[0]):
            print(json.dumps({"workload": name, **row}))


if __name__ == "__main__":
    main(sys.argv[1:])
