"""Headline timings; prints one JSON line. BENCH_SF_DIR, BENCH_CPUS and BENCH_RUNS set the run."""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from deltamat.functions import semiring as sr
    from deltamat.operators import dynamic_algebraic as alg
    from deltamat.operators import dynamic_general as gen
    from deltamat.operators import multiply, updates
    from deltamat.operators.layout import Grid
    from deltamat.queries.base import MAKE
    from deltamat.sources import instances as inst
    from deltamat.sources.scratch import materialize, new_path
    from deltamat.sources.store import DeltaStore, MatrixStore, StaticStore

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(CPUS)))
        .config("spark.driver.memory", "5g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="deltamat-bench-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def run(name: str, f) -> None:
        best = float("inf")
        for _ in range(int(os.environ.get("BENCH_RUNS", "2"))):
            began = time.perf_counter()
            out = f()
            if out is not None and hasattr(out, "write"):
                out.write.format("noop").mode("overwrite").save()
            best = min(best, time.perf_counter() - began)
        took[name] = round(best, 3)

    a = materialize(inst.draw(inst.order_part(spark, SF), 7), "order_part")
    b = materialize(inst.part_supp(spark, SF), "part_supp")
    n, k, m = inst.dims(spark, SF, ("orders", "o_orderkey"), ("part", "p_partkey"), ("supplier", "s_suppkey"))
    ga, gb = Grid(n, k, 2), Grid(k, m, 2)
    old = materialize(a.where("u < 500000").select("i", "j", "v"), "old")
    run("construct_order_part", lambda: MAKE["order_part"](spark, SF))
    run("static_product", lambda: multiply.spgemm(old, b))
    run("static_product_grid", lambda: multiply.spgemm_grid(old, b, ga, gb))
    c_old = materialize(multiply.spgemm(old, b), "c")
    c_star = materialize(alg.delta_product(old, a.where("u >= 500000 and u < 510000").select("i", "j", "v"), b, None), "c_star")
    for parts in (1000, 10_000, 50_000):
        star = materialize(a.where(f"u >= 500000 and u < {500_000 + parts}").select("i", "j", "v"), "star")
        run(f"delta_product_{parts / 10_000:g}pct", lambda star=star: alg.delta_product(old, star, b, None))
        run(f"delta_by_static_grid_{parts / 10_000:g}pct", lambda star=star: multiply.spgemm_grid(star, b, ga, gb))
    run("add_delta_1pct_to_product", lambda: alg.maintain(c_old, c_star))
    # (min, +) on the same operands, whose product has many terms a cell: deletions, raises, insertions.
    # An update ends with the cells that a block store appends; recomputing ends with the whole product.
    view = materialize(gen.product_with_bits(old, b, sr.MIN_PLUS), "view")
    run("general_recompute", lambda: gen.product_with_bits(old, b, sr.MIN_PLUS))
    # By rows; at 1 % also with fingerprints, which read the stored product.
    for name, t, variant in (("0.1pct", 333, "none"), ("1pct", 3333, "none"), ("5pct", 16_667, "none"), ("bits_1pct", 3333, "bits")):
        x_new = materialize(a.where(f"u >= {t} and u < {500_000 + t}").select("i", "j", F.when(F.col("u") < 2 * t, F.col("v") + 100).otherwise(F.col("v")).alias("v")), "new")
        x_star = materialize(a.where(f"u < {2 * t} or u >= 500000 and u < {500_000 + t}").select("i", "j"), "star")
        run(f"general_update_{name}", lambda x_new=x_new, x_star=x_star, variant=variant: gen.maintain_general(view, old, x_new, x_star, b, None, sr.MIN_PLUS, variant=variant).z)
    batch = updates.UpdateBatch.build(a.where("u >= 500000 and u < 510000").select("i", "j", "v"), 0)
    for kind in (DeltaStore, MatrixStore, StaticStore):
        stores = iter([kind.create(old, new_path(spark, "store"), Grid(n, k, 4)) for _ in range(int(os.environ.get("BENCH_RUNS", "2")))])
        run(f"insert_1pct_{kind.__name__}", lambda stores=stores: next(stores).apply(batch) and None)
    star = a.where("u < 100000")
    for method in ("one_step", "two_step", "sort"):
        run(f"redistribute_{method}", lambda method=method: updates.redistribute(star, Grid(n, k, 4), method))
    print(json.dumps({"metric": "headline_seconds_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF}))


if __name__ == "__main__":
    main()
