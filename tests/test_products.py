"""Worked examples, invariants and edge cases of the products."""

import random
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from deltamat.functions import semiring as sr
from deltamat.operators import dynamic_algebraic as alg
from deltamat.operators import dynamic_general as gen
from deltamat.operators import blocks, graphs, matrix, multiply, tiles, updates, walks
from deltamat.operators.dense import dense_product
from deltamat.operators.layout import Affine, Grid, assign_grid, from_csr, from_dcsr, permute, to_csr, to_dcsr, unpermute
from deltamat.plans.planner import ResultTooLarge, choose
from deltamat.plans.stored import StoredProduct
from deltamat.plans.view import ProductView
from deltamat.sources.scratch import new_path
from deltamat.sources.store import ConcurrentCommit, DeltaStore, MatrixStore, StaticStore

A = {(0, 0): 2, (0, 1): 5, (1, 1): 1, (2, 2): 4}
B = {(0, 0): 3, (0, 2): 7, (1, 0): 1, (1, 1): 6, (2, 1): 2}


def frame(spark, cells, value="long"):
    return spark.createDataFrame([(i, j, v) for (i, j), v in cells.items()], f"i long, j long, v {value}")


def cells(df, *extra):
    return {(r.i, r.j): r.v if not extra else (r.v, *(r[c] for c in extra)) for r in df.collect()}


def product(a, b, s):
    out = {}
    for (i, k), x in a.items():
        for (k2, j), y in b.items():
            if k == k2:
                t = s.py_times(x, y)
                out[i, j] = s.py_plus(out[i, j], t) if (i, j) in out else t
    return out


def test_static_example(spark):
    a, b = frame(spark, A), frame(spark, B)
    assert cells(multiply.spgemm(a, b)) == {(0, 0): 11, (0, 1): 30, (0, 2): 14, (1, 0): 1, (1, 1): 6, (2, 1): 8}
    assert cells(gen.product_with_bits(a, b, sr.MIN_PLUS), "bits") == {(0, 0): (5, 3), (0, 1): (11, 2), (0, 2): (9, 1), (1, 0): (2, 2), (1, 1): (7, 2), (2, 1): (6, 4)}


def test_algebraic_example_keeps_stored_zeros(spark):
    a, b = frame(spark, A), frame(spark, B)
    a_star, b_star = frame(spark, {(2, 0): 10, (0, 1): -5}), frame(spark, {(1, 2): 8})
    want = {(0, 0): -5, (0, 1): -30, (0, 2): 0, (1, 2): 8, (2, 0): 30, (2, 2): 70}
    for form in alg.FORMS:
        star = alg.delta_product(a, a_star, b, b_star, form=form)
        assert cells(star) == want
    c = alg.maintain(multiply.spgemm(a, b), star)
    assert cells(c) == {(0, 0): 6, (0, 1): 0, (0, 2): 14, (1, 0): 1, (1, 1): 6, (1, 2): 8, (2, 0): 30, (2, 1): 8, (2, 2): 70}
    a_new, b_new = updates.apply_add(a, a_star), updates.apply_add(b, b_star)
    assert matrix.equals(c, multiply.spgemm(a_new, b_new))


def test_general_example_sees_terms_that_lose_both_factors(spark):
    a, b = frame(spark, A), frame(spark, B)
    a_new = frame(spark, {(0, 0): 9, (0, 1): 5, (2, 2): 4})
    b_new = frame(spark, {k: v for k, v in B.items() if k != (1, 1)} | {(2, 0): 1})
    a_star, b_star = frame(spark, {(0, 0): 1, (1, 1): 1}).drop("v"), frame(spark, {(1, 1): 1, (2, 0): 1}).drop("v")
    c = gen.product_with_bits(a, b, sr.MIN_PLUS)
    steps = gen.maintain_general(c, a, a_new, a_star, b_new, b_star, sr.MIN_PLUS)
    bits = lambda df: {(r.i, r.j): r.bits for r in df.collect()}
    assert bits(steps.pattern) == {(0, 0): 1, (0, 1): 2, (0, 2): 1, (1, 0): 2, (1, 1): 2, (2, 0): 4}
    assert bits(steps.needed) == {(0, 0): 3, (0, 1): 2, (0, 2): 1, (1, 0): 2, (1, 1): 2, (2, 0): 4}
    assert {r.i: r.bits for r in steps.rows.collect()} == {0: 3, 1: 2, 2: 4}
    assert cells(steps.filtered) == {(0, 0): 9, (0, 1): 5, (2, 2): 4}
    assert cells(steps.z) == {(0, 0): 6, (0, 2): 16, (2, 0): 5}
    assert cells(steps.result, "bits") == {(0, 0): (6, 3), (0, 2): (16, 1), (2, 0): (5, 4), (2, 1): (6, 4)}
    # With the new A in place of the old one the cell (1, 1) would be missed.
    assert (1, 1) not in bits(gen.compute_pattern(a_new, a_star, b_new, b_star))


@pytest.mark.parametrize("name", ["plus_times", "min_plus", "max_min", "or_and"])
def test_random_histories(spark, name):
    s, rng = sr.ALL[name], random.Random(name)
    kind = "boolean" if name == "or_and" else "long"
    value = (lambda: rng.random() < 0.7) if kind == "boolean" else (lambda: rng.randint(-4, 9))
    n = 9
    draw = lambda k: {(rng.randrange(n), rng.randrange(n)): value() for _ in range(k)}
    a, b = draw(20), draw(20)
    view = ProductView.create(frame(spark, a, kind), frame(spark, b, kind), s)
    for step in range(3):
        batches = []
        for m in (a, b):
            rows = []
            for key in rng.sample(sorted(m), 3):
                if rng.random() < 0.5:
                    rows.append((*key, None, "del", step))
                    del m[key]
                else:
                    m[key] = value()
                    rows.append((*key, m[key], "set", step))
            for key, v in draw(3).items():
                if key not in m:
                    m[key] = v
                    rows.append((*key, v, "set", step))
            batches.append(updates.UpdateBatch.build(spark.createDataFrame(rows, f"i long, j long, v {kind}, op string, seq long"), step))
        view.update(*batches, batch_id=step, method="general", side=("left", "right")[step % 2])
        assert cells(view.result()) == product(a, b, s)
        fresh = gen.product_with_bits(view.a, view.b, s)
        assert cells(view.c, "bits") == cells(fresh, "bits")
    before = cells(view.result())
    assert view.update(*batches, batch_id=step).method == "none"
    assert cells(view.result()) == before


NAT = sr.Semiring.define("nat", F.sum, lambda a, b: a + b, lambda a, b: a * b, 0, 1, py_plus=lambda a, b: a + b, py_times=lambda a, b: a * b)


def test_adds_without_subtraction_are_not_counted_twice(spark):
    """(+, ·) without a minus is neither a ring nor idempotent: an add is its own delta."""
    view = ProductView.create(frame(spark, {(0, 0): 1}), frame(spark, {(0, 0): 1}), NAT)
    batch = updates.UpdateBatch.build(spark.createDataFrame([(0, 0, 2, "add", 0)], "i long, j long, v long, op string, seq long"))
    assert updates.classify(view.a, batch, NAT) == "algebraic"
    view.update(batch, batch_id=0, method="algebraic")
    assert cells(view.result()) == {(0, 0): 3} and view.verify().isEmpty()
    assert "method algebraic" in view.explain() and "HashAggregate" in view.explain()
    assert [(r.version, r.method, r.nnz_c) for r in view.snapshots().collect()] == [(0, "algebraic", 1)]
    assert updates.classify(view.a, batch, sr.COUNT_PAIR) == "general"  # counts pairs of cells, whatever they hold


def additive(spark, s, m, rng, n, value, step):
    """A batch that s can write as an addition, applied to the dictionary m as well."""
    rows = []
    for key in rng.sample(sorted(m), 3):
        how, v = rng.choice(("add", "same", "lower")), value()
        if how == "same":
            rows.append((*key, m[key], "set", step))
        elif how == "lower" and (s.idempotent or s.is_ring):
            m[key] = v if s.is_ring else s.py_plus(m[key], v)
            rows.append((*key, m[key], "set", step))
        else:
            m[key] = s.py_plus(m[key], v)
            rows.append((*key, v, "add", step))
    for _ in range(3):
        key, v = (rng.randrange(n), rng.randrange(n)), value()
        if key not in m and all(r[:2] != key for r in rows):
            m[key] = v
            rows.append((*key, v, rng.choice(("set", "add")), step))
    if s.is_ring:
        key = rng.choice([k for k in sorted(m) if all(r[:2] != k for r in rows)])
        del m[key]
        rows.append((*key, None, "del", step))
    return updates.UpdateBatch.build(spark.createDataFrame(rows, "i long, j long, v long, op string, seq long"), step)


@pytest.mark.parametrize("s", [sr.PLUS_TIMES, sr.MIN_PLUS, NAT], ids=lambda s: s.name)
def test_random_additive_histories(spark, s):
    """The planner's own classification, all three forms, on views and on block stores."""
    rng, n = random.Random(s.name), 9
    value = lambda: rng.randint(1, 9)
    draw = lambda k: {(rng.randrange(n), rng.randrange(n)): value() for _ in range(k)}
    a, b = draw(20), draw(20)
    view = ProductView.create(frame(spark, a), frame(spark, b), s)
    stored = StoredProduct.create(frame(spark, a), frame(spark, b), (n, n, n), new_path(spark, "product"), s, q=3)
    for step in range(2):
        batches = [additive(spark, s, m, rng, n, value, step) for m in (a, b)]
        assert updates.classify(view.a, batches[0], s) == "algebraic"
        view.update(*batches, batch_id=step, method="algebraic", form=alg.FORMS[(step + len(s.name)) % 3])
        assert stored.update(*batches, batch_id=step) == "algebraic"
        want = product(a, b, s)
        zeros = lambda df: {k: v for k, v in cells(df).items() if k in want or v != s.zero}  # noqa: E731  a ring's deletions leave stored zeros
        assert zeros(view.result()) == want == zeros(stored.result())
    assert stored.update(*batches, batch_id=step) == "none" and cells(stored.a.current()) == a
    if not s.is_ring:
        assert cells(view.c, "bits") == cells(gen.product_with_bits(view.a, view.b, s), "bits") == cells(stored.c.current(), "bits")


def test_general_history_on_block_stores(spark):
    """Deletions and raises; folding and clearing old versions change nothing."""
    rng, n, s = random.Random(3), 9, sr.MIN_PLUS
    a, b = ({(rng.randrange(n), rng.randrange(n)): rng.randint(1, 9) for _ in range(25)} for _ in "ab")
    stored = StoredProduct.create(frame(spark, a), frame(spark, b), (n, n, n), new_path(spark, "product"), s, q=3)
    for step in range(2):
        batches = []
        for m in (a, b):
            rows = []
            for key in rng.sample(sorted(m), 4):
                if rng.random() < 0.5:
                    rows.append((*key, None, "del", 0))
                    del m[key]
                else:
                    m[key] += 5
                    rows.append((*key, m[key], "set", 0))
            batches.append(updates.UpdateBatch.build(spark.createDataFrame(rows, "i long, j long, v long, op string, seq long")))
        assert stored.update(*batches, batch_id=step) == "general"
        fresh = gen.product_with_bits(frame(spark, a), frame(spark, b), s)
        assert cells(stored.c.current(), "bits") == cells(fresh, "bits")
        if step == 0:
            stored.compact()
            stored.vacuum(1)
    assert len(stored.c.versions()) == 2 and cells(stored.a.current()) == a


def test_blocks_that_a_batch_does_not_concern_are_not_read(spark):
    """A delta in one inner block reads that block row of the other operand and writes one block row of C."""
    m = {(i, j): i + j for i in range(8) for j in range(8)}
    stored = StoredProduct.create(frame(spark, m), frame(spark, m), (8, 8, 8), new_path(spark, "product"), q=4)
    read = []
    real = MatrixStore._blocks
    try:
        MatrixStore._blocks = lambda self, manifest: read.extend((self.root[-1], r.bi, r.bj) for r in manifest.where("nnz > 0").select("bi", "bj").collect()) or real(self, manifest)
        batch = updates.UpdateBatch.build(spark.createDataFrame([(0, 7, 3, "add", 0)], "i long, j long, v long, op string, seq long"))
        stored.update(batch, batch_id=0)
    finally:
        MatrixStore._blocks = real
    assert {x for x in read if x[0] == "a"} == {("a", 0, 3)} and {x[1] for x in read if x[0] == "b"} == {3} and not [x for x in read if x[0] == "c"]
    assert {(r.bi) for r in stored.c.manifest().where("written = 1").collect()} == {0}
    assert cells(stored.result()) == product(m | {(0, 7): 10}, m, sr.PLUS_TIMES)


def test_two_writers_of_one_version_do_not_both_win(spark):
    s = MatrixStore.create(frame(spark, A), new_path(spark, "store"), Grid(3, 3, 1))
    batch = lambda v, k: updates.UpdateBatch.build(spark.createDataFrame([(0, 0, v, "set", 0)], "i long, j long, v long, op string, seq long"), k)
    object.__setattr__(s, "version", lambda: 0)
    assert s.apply(batch(50, 1)) == 1
    with pytest.raises(ConcurrentCommit):
        MatrixStore.apply(s, batch(60, 2))
    object.__delattr__(s, "version")
    assert cells(s.current())[0, 0] == 50
    s.apply(batch(70, 3))
    assert s.vacuum(1) == [0, 1] and cells(s.current())[0, 0] == 70


def test_triangles_after_insertions(spark):
    rng = random.Random(6)
    edges = {tuple(sorted(rng.sample(range(9), 2))) for _ in range(26)}
    old, new = sorted(edges)[::2], sorted(edges)[1::2]
    df = lambda e: spark.createDataFrame([(i, j, 1) for i, j in e], "i long, j long, v long")
    whole = graphs.triangles(df(edges)).first().triangles
    assert graphs.triangles_after(graphs.triangles(df(old)), df(old), df(new + old[:2])).first().triangles == whole > 0


def test_laws_hold_and_are_told_apart():
    for s in (sr.PLUS_TIMES, sr.MIN_PLUS, sr.MAX_MIN, sr.MIN_MAX):
        assert all(sr.check_laws(s, [1, 2, 5]).values()), s.name
    assert sr.check_laws(sr.MIN_PLUS, [1, 2])["idempotent"] and "idempotent" not in sr.check_laws(sr.PLUS_TIMES, [1, 2])
    wrong = sr.Semiring.define("wrong", F.sum, None, None, 0, py_plus=lambda a, b: a + b, py_times=lambda a, b: a * b, idempotent=True)
    assert not sr.check_laws(wrong, [1, 2])["idempotent"]
    broken = sr.Semiring.define("broken", F.sum, None, None, 0, py_plus=lambda a, b: a - b, py_times=lambda a, b: a * b)
    assert not sr.check_laws(broken, [1, 2, 3])["plus_associative"]


def test_empty_and_total_batches(spark):
    a, b = frame(spark, A), frame(spark, B)
    none = matrix.empty(spark)
    assert cells(multiply.spgemm(a, none)) == {}
    assert cells(alg.delta_product(a, none, b, None)) == {}
    view = ProductView.create(a, b, sr.MIN_PLUS)
    assert view.update(updates.UpdateBatch.build(none.withColumn("op", F.lit("set")))).method == "none"
    gone = a.withColumn("op", F.lit("del"))
    view.update(updates.UpdateBatch.build(gone), method="general")
    assert cells(view.result()) == {} and view.verify().isEmpty()


def test_bits_wrap_at_64(spark):
    a, b = frame(spark, {(0, 63): 1, (0, 127): 2, (0, 5): 3}), frame(spark, {(63, 0): 1, (127, 0): 1, (5, 0): 1})
    bits = cells(gen.product_with_bits(a, b, sr.PLUS_TIMES), "bits")[0, 0][1]
    assert bits == (1 << 5) - (1 << 63)
    r = spark.createDataFrame([(0, -(1 << 63))], "i long, bits long")
    assert set(cells(gen.filter_left(a, r))) == {(0, 63), (0, 127)}


def test_batch_rows_resolve_in_order(spark):
    rows = [(0, 0, 1, "add", 1), (0, 0, 2, "add", 2), (1, 1, 7, "set", 1), (1, 1, 3, "add", 2), (2, 2, 9, "add", 1), (2, 2, None, "del", 2), (0, 1, None, "del", 1), (0, 1, 4, "add", 2)]
    batch = updates.UpdateBatch.build(spark.createDataFrame(rows, "i long, j long, v long, op string, seq long"))
    assert cells(updates.apply_ops(frame(spark, A), batch)) == {(0, 0): 5, (0, 1): 4, (1, 1): 10}


def test_classifier(spark):
    a = frame(spark, A)
    batch = lambda op, v: updates.UpdateBatch.build(spark.createDataFrame([(0, 0, v, op, 0)], "i long, j long, v long, op string, seq long"))
    assert updates.classify(a, batch("set", 1), sr.MIN_PLUS) == "algebraic"
    assert updates.classify(a, batch("set", 3), sr.MIN_PLUS) == "general"
    assert updates.classify(a, batch("del", None), sr.MIN_PLUS) == "general"
    assert updates.classify(a, batch("del", None), sr.PLUS_TIMES) == "algebraic"


def test_layouts_and_permutations(spark):
    a, g = frame(spark, A), Grid(3, 3, 2)
    assert cells(from_dcsr(to_dcsr(a, g))) == A == cells(from_csr(to_csr(a, g)))
    assert all(len(r.row_ptr) == {0: 3, 1: 2}[r.bi] for r in to_csr(a, g).collect())
    p = Affine(3, 2, 1)
    assert cells(unpermute(permute(a, p, p), p, p)) == A
    with pytest.raises(ValueError):
        Affine(6, 3)


def test_grid_of_one_block_moves_nothing(spark):
    a, b = frame(spark, A), frame(spark, B)
    g = Grid(3, 3, 1)
    star, volume = alg.simulate_rounds(a, frame(spark, {(2, 0): 10}), b, matrix.empty(spark), g, g)
    assert {r.step: r.cells for r in volume.collect()} == {"transposed_send": 0, "broadcast": 0, "reduce": 0}
    assert cells(multiply.spgemm_grid(a, b, g, g)) == product(A, B, sr.PLUS_TIMES)


def test_strategies_agree(spark):
    rng = random.Random(1)
    a = {(rng.randrange(12), rng.randrange(12)): rng.randint(1, 9) for _ in range(50)}
    x, g = frame(spark, a), Grid(12, 12, 3)
    want = product(a, a, sr.PLUS_TIMES)
    for out in (multiply.spgemm_grid(x, x, g, g), multiply.spgemm_rowpart(x, x, 3), multiply.spgemm_rowwise(x, x), multiply.spgemm_stationary(x, x, keep="left"), multiply.spgemm_stationary(x, x, cells=1), multiply.spgemm_salted(x, x, heavy=5, pieces=3), multiply.spgemm_layered(x, x, 2), multiply.spgemm_generic(x, x)):
        assert cells(out) == want


@pytest.mark.parametrize("kind", [MatrixStore, StaticStore, DeltaStore])
def test_store_touches_named_blocks_only_and_replays_once(spark, kind):
    m = {(i, j): i + j for i in range(8) for j in range(0, 8, 2)}
    s = kind.create(frame(spark, m), new_path(spark, "store"), Grid(8, 8, 4))
    batch = updates.UpdateBatch.build(spark.createDataFrame([(0, 0, 50, "set", 1), (1, 0, None, "del", 1), (0, 1, 7, "set", 1)], "i long, j long, v long, op string, seq long"), 3)
    assert s.apply(batch) == 1 == s.apply(batch)
    want = {**{k: v for k, v in m.items() if k != (1, 0)}, (0, 0): 50, (0, 1): 7}
    assert cells(s.current()) == want and cells(s.at(0)) == m
    assert cells(s.get(0, 0)) == {(0, 0): 50} and cells(s.row(0)) == {k: v for k, v in want.items() if k[0] == 0}
    rewritten = s.manifest().where("written = 1").count()
    assert rewritten == (s.manifest().count() if kind is StaticStore else 1)
    s.apply(updates.UpdateBatch.build(spark.createDataFrame([(0, 0, 5, "add", 1), (7, 7, 2, "add", 1), (1, 0, 3, "add", 1)], "i long, j long, v long, op string, seq long"), 4))
    want |= {(0, 0): 55, (7, 7): 2, (1, 0): 3}
    assert cells(s.current()) == want
    assert cells(matrix.select(s.at(s.compact()), "true")) == want


def test_delta_product_shuffles_partials_only(spark):
    """No exchange between the scan of the large operand and the join with the broadcast delta."""
    b = spark.read.parquet(_written(spark, B))
    plan = alg.delta_product(frame(spark, A), frame(spark, {(2, 0): 10}), b, None)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "BroadcastHashJoin" in plan


def test_mask_is_tested_before_values_are_folded(spark):
    b = spark.read.parquet(_written(spark, B))
    plan = multiply.spgemm_masked(b, b, b.limit(2))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Aggregate") < plan.index("Join LeftSemi, ((i")


def _written(spark, m):
    path = new_path(spark, "cells")
    frame(spark, m).write.parquet(path)
    return path


def test_planner_follows_the_batch():
    n = {"a": 10**6, "b": 10**6, "c": 10**7, "b_star": 0, "flops": 10**8}
    small = choose(n | {"a_star": 100, "flops_delta": 10_000}, "algebraic")
    large = choose(n | {"a_star": 10**6, "flops_delta": 10**8}, "algebraic")
    assert small.method == "algebraic" and large.method in ("recompute", "delta_static")
    assert choose(n | {"a_star": 0, "flops_delta": 0}, "general").method == "none"
    with pytest.raises(ResultTooLarge):
        choose(n | {"a_star": 5, "flops_delta": 10}, "general", most_cells=10)


def test_blocks_cover_the_grid(spark):
    m = frame(spark, {(i, i): 1 for i in range(10)})
    laid = assign_grid(m, Grid(10, 10, 3))
    assert {(r.bi, r.bj) for r in laid.collect()} == {(0, 0), (1, 1), (2, 2)}


def test_broadcast_product_is_bounded(spark):
    a, b = frame(spark, A), frame(spark, B)
    plan = lambda df: df._jdf.queryExecution().optimizedPlan().toString()
    for bound in (len(B), len(B) - 1):
        df = multiply.spgemm(a, b, strategy="broadcast", cells=bound)
        assert ("strategy=broadcast" in plan(df)) == (bound == len(B))
        assert cells(df) == product(A, B, sr.PLUS_TIMES)


@pytest.mark.parametrize("name", sorted(sr.ALL))
def test_layers_take_one_exchange_of_terms(spark, name):
    s, rng = sr.ALL[name], random.Random(name)
    value = (lambda: True) if name == "or_and" else (lambda: rng.randrange(1, 9))
    a, b = ({(rng.randrange(6), rng.randrange(9)): value() for _ in range(20)} for _ in range(2))
    x, y = (frame(spark, m, "boolean" if name == "or_and" else "long") for m in (a, b))
    df = multiply.spgemm_layered(x, y, 3, s)
    assert cells(df) == product(a, b, s)
    assert df._jdf.queryExecution().optimizedPlan().toString().count("Aggregate [") == 1


def walk_graph(seed: int):
    """Ids far apart, loops, vertices without edges out, and a component of its own."""
    rng = random.Random(seed)
    ids = [rng.randrange(10**9) for _ in range(14)]
    g = {(rng.choice(ids[:9]), rng.choice(ids[:12])): rng.randrange(1, 9) for _ in range(30)}
    return g | {(ids[12], ids[13]): 3, (ids[13], ids[13]): 2}


@pytest.mark.parametrize("hops", [0, 1, 3])
def test_paths_in_one_pass_are_those_of_products(spark, hops, monkeypatch):
    monkeypatch.setattr(walks, "BLOCK", 4)
    g = frame(spark, walk_graph(hops))
    sources = spark.createDataFrame([(i,) for i in {k[0] for k in walk_graph(hops)} | {-5}], "i long")
    fast, slow = walks.paths(g, sources, hops), graphs.shortest_paths(g, sources, hops, cells=3)
    assert cells(fast) == cells(slow) and (-5, -5) in cells(fast)
    assert "MapInArrow" in fast._jdf.queryExecution().executedPlan().toString()
    assert cells(graphs.bfs(g, sources, hops)) == cells(graphs.bfs(g, sources, hops, cells=3))
    assert walks.paths(g, sources, hops, cells=3) is None and walks.paths(g.withColumn("v", F.lit(1 << 60)), sources, 3) is None
    assert walks.paths(g.withColumn("v", F.lit(None).cast("long")), sources, hops) is None


def test_reachability_in_one_pass_is_that_of_squaring(spark, monkeypatch):
    monkeypatch.setattr(walks, "BLOCK", 4)
    g = frame(spark, dict.fromkeys(walk_graph(5), True), "boolean")
    fast = multiply.closure(g, sr.OR_AND)
    assert cells(fast) == cells(multiply.closure(g, sr.OR_AND, cells=3))
    assert "MapInArrow" in fast._jdf.queryExecution().executedPlan().toString()
    assert walks.reachable(g.withColumn("v", F.col("i") < F.col("j"))) is None
    assert multiply.closure(g.where("false"), sr.OR_AND).isEmpty()


def test_reachability_takes_each_component_once():
    """A block of a path of 4,000 vertices took minutes, since vertices were looked at again for each length of a path."""
    rng = np.random.default_rng(3)
    for n, m in ((1, 0), (1, 1), (12, 9), (12, 16), (30, 45), (30, 200)):
        i, j = np.unique(rng.integers(0, n, (2, m)), axis=1)
        g = walks.condensed(walks.Graph(np.arange(n) * 7, np.searchsorted(i, np.arange(n + 1)), j.astype(np.int32), np.ones(len(i), np.int64)))
        far = np.zeros((n, n), bool)
        far[i, j] = True
        for k in range(n):
            far |= far[:, k, None] & far[k]
        got = [(a, b) for s, b, _ in walks.reach_rows(g, np.arange(n) * 7) for a, b in zip(s.tolist(), (b // 7).tolist(), strict=True)]
        assert sorted(got) == [tuple(x) for x in np.argwhere(far).tolist()]
        assert (g.of[i] >= g.of[j]).all() and [far[k, k] for k in range(n)] == g.cyclic[g.of].tolist()
    n, began = 4000, time.process_time()
    path = walks.Graph(np.arange(n), np.minimum(np.arange(n + 1), n - 1), np.arange(1, n, dtype=np.int32), np.ones(n - 1, np.int64))
    assert sum(len(s) for s, _, _ in walks.reach_rows(walks.condensed(path), np.arange(1024))) == sum(n - 1 - k for k in range(1024))
    assert time.process_time() - began < 10


@pytest.mark.parametrize("t", [2, 3])
def test_powers_in_one_pass_are_those_of_products(spark, t, monkeypatch):
    monkeypatch.setattr(walks, "BLOCK", 4)
    g = frame(spark, walk_graph(t))
    twice = g.unionByName(g.where("v > 4"))
    for m in (g, twice):
        fast = multiply.power(m, t)
        assert cells(fast) == cells(multiply.power(m, t, cells=3))
        assert "MapInArrow" in fast._jdf.queryExecution().executedPlan().toString()
    assert walks.positive_power(g.withColumn("v", F.col("v") - 3), t) is None and walks.positive_power(g.withColumn("v", F.lit(1 << 40)), t) is None


def test_dense_rows_are_the_product(spark, monkeypatch):
    monkeypatch.setattr(walks, "BLOCK", 4)
    rng = random.Random(11)
    m = frame(spark, {(rng.randrange(11) * 10**6, rng.randrange(70)): rng.randrange(1, 9) for _ in range(300)})
    twice = m.unionByName(m.where("v > 4"))
    for d in (m, twice):
        got = dense_product(d, d, (False, True), bits=True)
        assert cells(got.drop("bits")) == cells(multiply.spgemm(d, d, trans=(False, True)))
    assert cells(dense_product(m, m, (False, True), bits=True), "bits") == cells(gen.product_with_bits(m, matrix.transpose(m).select("i", "j", "v"), sr.PLUS_TIMES), "bits")
    assert cells(graphs.cosine(m)) == cells(graphs.cosine(m, cells=3))
    assert "MapInArrow" in graphs.cosine(m)._jdf.queryExecution().executedPlan().toString()
    for refused in (m.withColumn("v", F.col("v") - 5), m.withColumn("v", F.lit(1 << 40)), m.withColumn("v", F.lit(1.5)), m.where("false")):
        assert dense_product(refused, refused, (False, True)) is None


def test_a_nearly_full_change_is_made_by_rows(spark):
    rng = random.Random(12)
    m = {(rng.randrange(11), rng.randrange(20)): rng.randrange(1, 9) for _ in range(150)}
    right = frame(spark, {(k, i): v for (i, k), v in m.items()})
    batch = lambda lo: updates.UpdateBatch.build(frame(spark, {c: v for c, v in m.items() if c[0] % 2 == lo}).withColumn("op", F.lit("add")), lo)
    want = product(m, {(k, i): v for (i, k), v in m.items()}, sr.PLUS_TIMES)
    stored = StoredProduct.create(matrix.empty(spark), right, (11, 20, 11), new_path(spark, "product"), q=2)
    view = ProductView.create(matrix.empty(spark), right, bits=False)
    for lo in (0, 1):
        view.update(batch(lo), batch_id=lo, method="algebraic")
        assert "MapInArrow" in view.explain()
        assert stored.update(batch(lo), batch_id=lo) == "algebraic"
    assert cells(view.result()) == want == cells(stored.result())
    with_bits = cells(gen.product_with_bits(frame(spark, m), right, sr.PLUS_TIMES), "bits")
    assert cells(stored.c.current(), "bits") == with_bits


def hub_cells(seed: int, rows: int = 40) -> dict:
    """Cells with a hub row, a hub column, values of both signs and sums that cancel."""
    rng = random.Random(seed)
    out = {(rng.randrange(rows), rng.randrange(rows)): rng.choice([-2, -1, 1, 2]) for _ in range(200)}
    out |= {(3, j): 1 for j in range(rows)} | {(i, 5): -1 for i in range(rows)}
    return out | {(1000, 3): 7, (3, 10**12): 2}


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_row_partitioned_product_exchanges_no_terms(spark):
    x = frame(spark, hub_cells(2))
    out = multiply.spgemm_rowpart(x, x, 3)
    assert "FlatMapCoGroupsInArrow" in plan_of(out) and "sum(" not in plan_of(out)
    assert cells(out) == product(hub_cells(2), hub_cells(2), sr.PLUS_TIMES)

@pytest.mark.parametrize("step", [1, 7, 1 << 20])
@pytest.mark.parametrize("sparse", [0, 32])
def test_block_sums_in_steps(monkeypatch, step, sparse):
    monkeypatch.setattr(blocks, "SPARSE", sparse)
    for seed, sign in ((1, 1), (2, -1)):
        a = {at: v if sign < 0 else abs(v) for at, v in hub_cells(seed).items()}
        i, k, av = (np.array(x, np.int64) for x in zip(*[(i, j, v) for (i, j), v in a.items()], strict=True))
        bk, bj, bv = (np.array(x, np.int64) for x in zip(*[(i, j, v) for (i, j), v in sorted(a.items())], strict=True))
        rk, at = np.unique(bk, return_index=True)
        for upper in (False, True):
            got = {}
            for p, q, v in blocks.block_sums(i, k, av, rk, np.r_[at, len(bk)], bj, bv, upper, step):
                got |= dict(zip(zip(p.tolist(), q.tolist(), strict=True), v.tolist(), strict=True))
            assert got == {c: v for c, v in product(a, a, sr.PLUS_TIMES).items() if not upper or c[0] < c[1]}


def test_block_product_in_many_blocks(spark):
    a = hub_cells(4)
    left, right = multiply.sides(frame(spark, a), frame(spark, a))
    cut = (F.col("k") % 2).alias("cut")
    out = blocks.block_product(left.select((F.col("i") % 2).alias("deal"), cut, "i", "k", "av"), right.select(cut, "k", "j", "bv"), spread=4, terms=40)
    got = {}
    for r in out.collect():
        got.setdefault((r.cut, r.i, r.j), []).append(r.v)
    want = {(c, *at): v for c in (0, 1) for at, v in product({x: v for x, v in a.items() if x[1] % 2 == c}, a, sr.PLUS_TIMES).items()}
    assert {at: v[0] for at, v in got.items()} == want and all(len(v) == 1 for v in got.values())


def test_block_product_refuses_what_it_cannot_add_exactly(spark):
    for rows in ([(1, 1, 1 << 31)], [(1, 1, None), (1, 2, 1)], [(None, 1, 1), (1, 1, 1)]):
        x = spark.createDataFrame(rows, "i long, j long, v long")
        out = multiply.spgemm_rowpart(x, x, 2)
        assert "CoGroups" not in plan_of(out)
        assert sorted(out.collect(), key=str) == sorted(multiply.spgemm(x, x).collect(), key=str)
    empty = spark.createDataFrame([], "i long, j long, v long")
    assert multiply.spgemm_rowpart(empty, empty, 2).collect() == []


def test_grid_product_works_in_blocks_of_rows(spark):
    x, g = frame(spark, {(i % 12, j % 12): v for (i, j), v in hub_cells(5).items()}), Grid(12, 12, 2)
    want = cells(multiply.spgemm(x, x))
    for grid in (g, Grid(12, 12, 3, None, Affine(12, 5), Affine(12, 7))):
        out = multiply.spgemm_grid(x, x, grid, grid)
        assert "FlatMapCoGroupsInArrow" in plan_of(out) and cells(out) == want
    least = x.withColumn("v", F.col("v") + 5)
    assert cells(multiply.spgemm_grid(least, least, g, g, sr.MIN_PLUS)) == cells(multiply.spgemm(least, least, sr.MIN_PLUS))


def test_grid_product_copies_cells_in_the_last_exchange_only(spark, monkeypatch):
    a = {(i % 12, j % 12): v for (i, j), v in hub_cells(5).items()}
    x, g = frame(spark, a), Grid(12, 12, 3, None, Affine(12, 5), Affine(12, 7))
    written, write = {}, blocks.materialize
    monkeypatch.setattr(blocks, "materialize", lambda df, name: written.setdefault(name, write(df, name)))
    out = multiply.spgemm_grid(x, x, g, g)
    assert written["dealt"].count() == len(a) and cells(out) == product(a, a, sr.PLUS_TIMES)
    nulls = x.unionByName(spark.createDataFrame([(None, 1, 1)], "i long, j long, v long"))
    assert "CoGroups" not in plan_of(multiply.spgemm_grid(nulls, x, g, g))


def test_triple_product_never_makes_the_large_half(spark):
    r, a = hub_cells(6, 12), hub_cells(7, 12)
    p = {(j, j % 3): 1 for j in range(12)} | {(10**12, 1): 1}
    out = graphs.triple_product(frame(spark, r), frame(spark, a), frame(spark, p))
    assert "FlatMapCoGroupsInArrow" in plan_of(out)
    assert cells(out) == product(product(r, a, sr.PLUS_TIMES), p, sr.PLUS_TIMES)
    huge = frame(spark, {(0, 0): 1 << 31})
    assert cells(graphs.triple_product(huge, huge, frame(spark, {(0, 0): 1}))) == {(0, 0): 1 << 62}


def test_two_hop_by_window_exchanges_no_pairs(spark):
    rng = random.Random(8)
    rows = [(rng.choice([None, 1, 5, 7, 10**12]), f"2024-01-0{rng.randint(1, 3)} 0{rng.randint(0, 9)}:00:00", rng.choice([None, "{}", '{"k": 1}', '{"k": 2}'])) for _ in range(120)]
    events = spark.createDataFrame(rows, "user_id long, ts string, props string").withColumn("ts", F.col("ts").cast("timestamp"))
    out = graphs.two_hop_by_window(events)
    assert "FlatMapCoGroupsInArrow" in plan_of(out)
    n = {}
    for u, ts, props in rows:
        if u is not None and props and "k" in props:
            n[ts[:10], u, props] = n.get((ts[:10], u, props), 0) + 1
    want = {}
    for (s, i, k), x in n.items():
        for (t, j, m), y in n.items():
            if s == t and k == m and i < j:
                want[s, i, j] = want.get((s, i, j), 0) + x * y
    assert {(str(r.start)[:10], r.i, r.j): r.v for r in out.collect()} == want


@pytest.mark.parametrize("share", [0, 5, 10**9])
def test_tiles_of_full_and_thin_columns(share):
    for seed, scale in ((1, 1), (2, 1 << 20)):
        a = {at: v * scale for at, v in hub_cells(seed).items()}
        i, j, v = (np.array(x, np.int64) for x in zip(*[(p, q, x) for (p, q), x in a.items()], strict=True))
        x = tiles.Block(*tiles.packed_block(i, j, v)[1:])
        full = np.array([[a.get((p, q), 0) for q in np.unique(j).tolist()] for p in x.ids.tolist()], float)
        assert (tiles.tile(x, x, share, 7) == full @ full.T).all()


def test_similarity_by_tiles_exchanges_no_terms(spark, monkeypatch):
    a = {(i, j): abs(v) for (i, j), v in hub_cells(9).items()}
    want = {at: v for at, v in product(a, {(j, i): v for (i, j), v in a.items()}, sr.PLUS_TIMES).items() if at[0] < at[1] and v >= 3}
    x = frame(spark, a).unionByName(spark.createDataFrame([(None, 3, 5), (4, None, 5), (5, 3, None)], "i long, j long, v long"))
    out = graphs.similarity(x, 3, tiled=True)
    assert "CartesianProduct" in plan_of(out) and "sum(" not in plan_of(out) and cells(out) == want
    parted = tiles.upper_products(x, 3, cells=60)
    assert cells(parted) == want == cells(graphs.similarity(x, 3))
    assert tiles.upper_products(frame(spark, {(0, 0): 1 << 31}), 3) is None
    assert graphs.similarity(frame(spark, {}), 3, tiled=True).collect() == []


def test_walks_hold_the_vertices_that_a_block_comes_to(spark, monkeypatch):
    """Graphs of over a million cells, or of more vertices than 32 sources' table had room for, were joined hop by hop."""
    rng = np.random.default_rng(8)
    n = 60
    m = np.zeros((n, n), np.int64)
    for k in range(0, n, 20):  # three graphs that do not meet
        i, j = rng.integers(k, k + 20, (2, 90))
        m[i, j] = rng.integers(1, 9, 90)
    i, j = np.nonzero(m)
    g = walks.Graph(np.arange(n) * 7, np.searchsorted(i, np.arange(n + 1)), j.astype(np.int32), m[i, j])
    monkeypatch.setattr(walks, "GATHERED", 64)
    for room in (64 << 20, 4000, 1):  # whole, halved, one source at a time
        monkeypatch.setattr(walks, "TABLE_BYTES", room)
        for kind in (np.float32, np.float64, np.int64):
            got = [x for s, b, v in walks.power_rows(3, kind)(g, g.ids) for x in zip(s.tolist(), (b // 7).tolist(), v.tolist(), strict=True)]
            want = np.linalg.matrix_power(m, 3)
            assert sorted(got) == [(*x, want[tuple(x)]) for x in np.argwhere(want).tolist()]
        least = np.where(np.eye(n, dtype=bool), 0, 1 << 40)
        for hops in (1, 2, 3):
            least = np.minimum(least, (least[:, :, None] + np.where(m, m, 1 << 40)).min(axis=1))
            for kind in (np.int16, np.int64):
                got = [x for s, b, v in walks.path_rows(hops, kind)(g, g.ids) for x in zip(s.tolist(), (b // 7).tolist(), v.tolist(), strict=True)]
                assert sorted(got) == [(*x, least[tuple(x)]) for x in np.argwhere(least < 1 << 40).tolist()]
    monkeypatch.undo()  # two million vertices, of which a source comes to three
    ids = spark.range(700_000).select((F.col("id") * 3).alias("i"))
    chain = ids.select("i", (F.col("i") + 1).alias("j"), F.lit(2).cast("long").alias("v")).unionByName(ids.select((F.col("i") + 1).alias("i"), (F.col("i") + 2).alias("j"), F.lit(-1).cast("long").alias("v")))
    some = ids.where("i % 2000 = 0")
    assert cells(walks.paths(chain, some, 2)) == {(3 * k + a, 3 * k + b): v for k in range(700_000) for a, b, v in ((0, 0, 0), (0, 1, 2), (0, 2, 1)) if 3 * k % 2000 == 0}


def test_layers_exchange_no_terms(spark):
    """Sums of products of layers were exchanged term by term, which took more disk than both operands many times over."""
    rng = np.random.default_rng(9)
    x, y = (np.where(rng.random((40, 30)) < 0.3, rng.integers(-4, 5, (40, 30)), 0) for _ in range(2))
    y = y.T.copy()
    i, k = np.nonzero(x)
    rk, j = np.nonzero(y)
    at = np.searchsorted(rk, np.arange(31))
    want = {(a, c): int((x @ y)[a, c]) for a, c in np.argwhere((x != 0).astype(int) @ (y != 0) > 0).tolist()}
    for step, sparse in ((1 << 18, 6), (50, 6), (1 << 18, 0), (50, 0)):  # a full table of sums, and sorted terms
        with pytest.MonkeyPatch.context() as m:
            m.setattr(blocks, "SPARSE", sparse)
            for layers in (1, 2, 3):
                got = [z for part in blocks.block_sums(i, k - 7, x[i, k], np.arange(30) - 7, at, j, y[rk, j], False, step, layers) for z in zip(*(c.tolist() for c in part), strict=True)]
                assert {z[:2]: z[2] for z in got} == want and len(got) == len(want)
    a, b = (frame(spark, {(int(p), int(q)): int(m[p, q]) for p, q in np.argwhere(m).tolist()}) for m in (x, y))
    df = multiply.spgemm_layered(a, b, 3)
    assert cells(df) == want == cells(multiply.spgemm_layered(a.withColumn("v", F.col("v").cast("int")), b, 3))
    assert "FlatMapCoGroupsInArrow" in df._jdf.queryExecution().executedPlan().toString()


def test_cosines_of_many_cells_are_made_by_tiles(spark):
    """Beyond the cells that tasks may hold, all terms were joined and exchanged."""
    rng = random.Random(13)
    m = frame(spark, {(rng.randrange(40) * 10**6, rng.randrange(12)): rng.randrange(1, 9) for _ in range(260)})
    m = m.unionByName(m.where("v > 5"))
    tiled = graphs.cosine(m, cells=3)
    assert "MapInArrow" in tiled._jdf.queryExecution().executedPlan().toString()
    assert cells(tiled) == cells(graphs.cosine(m)) and tiled.schema == graphs.cosine(m).schema
    signed = m.withColumn("v", F.col("v") - 4)
    assert "MapInArrow" not in graphs.cosine(signed, cells=3)._jdf.queryExecution().executedPlan().toString()
    sparse = frame(spark, {(k, k): 2 for k in range(40)})
    assert graphs.nearly_full(m) and not graphs.nearly_full(sparse) and not graphs.nearly_full(m.where("false"))
