"""Counts of work and movement, each as a table that SQL can check."""

from __future__ import annotations

import json
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.functions.semiring import Semiring
from deltamat.operators.dynamic_general import exact_left, filter_left
from deltamat.operators.layout import Affine, Grid, assign_grid
from deltamat.operators.multiply import flops, spgemm  # noqa: F401  flops is measure one

Row = tuple[str, int]


def nnz(df: DataFrame) -> int:
    return df.count()


def volume_static(a: DataFrame, b: DataFrame, q: int) -> DataFrame:
    """Cells moved by the static grid: every block goes to its q − 1 peers."""
    both = a.select("i").unionByName(b.select("i"))
    return both.agg((F.count("*") * (q - 1)).alias("cells"))


def volume_general(a_r: DataFrame, c_star: DataFrame, z_partials: DataFrame, ga: Grid, gb: Grid) -> DataFrame:
    """(step, cells) of a general update: A^R across the diagonal, copies, and partials away from home.

    z_partials: (pi, pj, i, j), one row for each producer and result cell.
    """
    q = ga.qr
    sent = a_r.agg(F.count_if(ga.bi(F.col("i")) != ga.bj(F.col("j"))).alias("cells")).select(F.lit("transposed_send").alias("step"), "cells")
    both = a_r.select("i").unionByName(c_star.select("i")).agg((F.count("*") * (q - 1)).alias("cells")).select(F.lit("broadcast").alias("step"), "cells")
    away = (F.col("pi") != ga.bi(F.col("i"))) | (F.col("pj") != gb.bj(F.col("j")))
    moved = z_partials.agg(F.count_if(away).alias("cells")).select(F.lit("reduce").alias("step"), "cells")
    return sent.unionByName(both).unionByName(moved)


def general_partials(a_r: DataFrame, b_new: DataFrame, c_star: DataFrame, gb: Grid) -> DataFrame:
    """(pi, pj, i, j): what the holders of B' produce for cells of C*."""
    left = a_r.select("i", F.col("j").alias("k"))
    terms = left.join(b_new.select(F.col("i").alias("k"), "j"), "k").join(c_star.select("i", "j"), ["i", "j"], "left_semi")
    return terms.select(gb.bi(F.col("k")).alias("pi"), gb.bj(F.col("j")).alias("pj"), "i", "j").distinct()


def bounds(spark: SparkSession, counts: dict[str, int], p: int) -> DataFrame:
    """(method, latency, bandwidth, work, memory): the asymptotic terms, constants left out.

    counts: a, b (new operands), a_star, b_star, c, c_star, a_r, flops, flops_delta, flops_general.
    """
    root, log = math.sqrt(p), math.log2(p) if p > 1 else 1.0
    n = counts
    most = max(n["a"], n["b"], n["c"]) / p
    rows = [
        ("redistribution", root, (n["a_star"] + n["b_star"]) / p, (n["a_star"] + n["b_star"]) / p + root, (n["a_star"] + n["b_star"]) / p),
        ("static", root * log, (n["a"] + n["b"]) / root, n["flops"] / p, most),
        ("algebraic", root * log, max(n["a_star"] + n["b_star"], n["c_star"]) / root, n["flops_delta"] * log / p, most),
        ("general", root * log, (n["a_r"] + n["c_star"]) / root, n["flops_general"] * log / p, most),
    ]
    return spark.createDataFrame([(m, *map(float, x)) for m, *x in rows], "method string, latency double, bandwidth double, work double, memory double")


def redistribution(trace: DataFrame) -> DataFrame:
    """(step, moved, peers): cells that change their process in each step, and most peers of one."""
    one = lambda name, a, b: trace.where(F.col(a) != F.col(b)).groupBy(a).agg(F.count("*").alias("n"), F.count_distinct(b).alias("p")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("moved"), F.coalesce(F.max("p"), F.lit(0)).alias("peers")).select(F.lit(name).alias("step"), "moved", "peers")
    return one("first", "src", "mid").unionByName(one("second", "mid", "dst")).unionByName(one("direct", "src", "dst"))


def balance(m: DataFrame, n: int, k: int, q: int, rows: Affine | None = None, cols: Affine | None = None) -> DataFrame:
    """(most, mean, ratio) of cells in a block, over all q × q blocks."""
    per = assign_grid(m, Grid(n, k, q, None, rows, cols)).groupBy("bi", "bj").agg(F.count("*").alias("n"))
    return per.agg(F.max("n").alias("most"), (F.sum("n") / (q * q)).alias("mean")).select("most", "mean", F.round(F.col("most") / F.col("mean"), 6).alias("ratio"))


def filter_effect(a_new: DataFrame, b_new: DataFrame, c_star: DataFrame, rows: DataFrame, ell: int = 64) -> DataFrame:
    """(all_cells, rows_only, filtered, exact): cells of A' that each filter leaves."""
    count = lambda df, name: df.agg(F.count("*").alias(name))
    only = a_new.join(c_star.select("i").distinct(), "i", "left_semi")
    parts = [count(a_new, "all_cells"), count(only, "rows_only"), count(filter_left(a_new, rows, ell), "filtered"), count(exact_left(a_new, b_new, c_star), "exact")]
    out = parts[0]
    for p in parts[1:]:
        out = out.crossJoin(p)  # single rows
    return out


def compression(a: DataFrame, b: DataFrame, s: Semiring) -> DataFrame:
    """(flops, nnz_c, factor)."""
    size = spgemm(a, b, s).agg(F.count("*").alias("nnz_c"))
    return flops(a, b).crossJoin(size).select("flops", "nnz_c", F.round(F.col("flops") / F.col("nnz_c"), 6).alias("factor"))


def spark_metrics(event_log: str) -> list[dict]:
    """Shuffle records and bytes of each stage in an event log (JSON lines)."""
    stages: dict[int, dict] = {}
    with open(event_log) as f:
        for text in f:
            e = json.loads(text)
            if e.get("Event") == "SparkListenerTaskEnd" and e.get("Task Metrics"):
                w = e["Task Metrics"]["Shuffle Write Metrics"]
                s = stages.setdefault(e["Stage ID"], {"stage": e["Stage ID"], "records": 0, "bytes": 0})
                s["records"] += w["Shuffle Records Written"]
                s["bytes"] += w["Shuffle Bytes Written"]
    return [stages[k] for k in sorted(stages)]
