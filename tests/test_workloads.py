"""The experiments at the smallest size: every contender runs, and counts move as they should."""

import pytest

from deltamat import workloads


def test_construction_covers_the_instances(spark, sf):
    rows = workloads.construction(spark, sf, ("part_supp", "order_cust"))
    assert {(r["instance"], r["contender"]) for r in rows} == {(n, c) for n in ("part_supp", "order_cust") for c in ("dynamic", "static_sorted", "static_dcsr")}


@pytest.mark.parametrize("name", ["insertion", "value_updates", "deletion"])
def test_batches_on_stores(spark, sf, name):
    rows = workloads.ALL[name](spark, sf, fractions=(0.01,), batches=2)
    assert len(rows) == 6 and all(r["seconds"] > 0 for r in rows)


def test_products_run_from_an_empty_operand(spark, sf):
    rows = workloads.dynamic_product(spark, sf, fractions=(0.01,), batches=2)
    assert {r["contender"] for r in rows} == {"delta", "delta_static", "recompute", "generic", "rowpart"} and len(rows) == 10


def test_general_products_follow_every_batch(spark, sf):
    rows = workloads.general_product(spark, sf, fractions=(0.03,), batches=2)
    assert {(r["batch"], r["contender"]) for r in rows} == {(k, w) for k in (0, 1) for w in ("masked", "recompute", "generic")}


def test_more_processes_move_more_cells(spark, sf):
    rows = workloads.product_breakdown(spark, sf, processes=(4, 16), per_process=20)
    assert rows[0]["cells_broadcast"] < rows[1]["cells_broadcast"] and {"send", "broadcast", "multiply", "multiply_reduce", "add"} <= rows[0].keys()
    rows = workloads.scaling_insert(spark, sf, processes=(4, 16), per_process=50, batches=1)
    assert rows[0]["cells"] < rows[1]["cells"] and {"first", "second", "sort", "insert"} <= rows[0].keys()


def test_power_law_graphs_grow_with_the_processes(spark, sf):
    rows = workloads.rmat_weak(spark, sf, scale=8, edges=500, parts=2, processes=(4, 16))
    assert {r["edges"] for r in rows if "edges" in r} == {2000, 8000}
    ratios = {(r["p"], r["balance"]): r["ratio"] for r in rows if "balance" in r}
    assert all(ratios[p, "permuted"] < ratios[p, "plain"] for p in (4, 16))
