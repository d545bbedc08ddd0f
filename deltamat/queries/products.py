"""Static products, their strategies and baselines; dynamic products by both methods."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamat.functions import semiring as sr
from deltamat.functions import sqltext
from deltamat.operators import baselines, matrix, multiply, updates
from deltamat.operators import dynamic_algebraic as alg
from deltamat.operators import dynamic_general as gen
from deltamat.operators.layout import Affine, Grid
from deltamat.plans.stored import StoredProduct
from deltamat.plans.view import ProductView
from deltamat.queries.base import MIN_SQL, SQL, bits_sql, cells, drawn, drawn_sql, product_sql, query
from deltamat.sources import instances as inst
from deltamat.sources.scratch import materialize, new_path

G6 = f"WITH a AS ({SQL['user_succ']}), b AS ({SQL['user_succ']}) "
AB = f"WITH a AS ({SQL['order_part']}), b AS ({SQL['part_supp']}) "


def succ(spark, d):
    m = cells(spark, d, "user_succ")
    return m, m


def order_supp(spark, d):
    return cells(spark, d, "order_part"), cells(spark, d, "part_supp")


def order_supp_grids(spark, d, q=2, perm=False) -> tuple[Grid, Grid]:
    n, k, m = inst.dims(spark, d, ("orders", "o_orderkey"), ("part", "p_partkey"), ("supplier", "s_suppkey"))
    p = (Affine(n), Affine(k), Affine(m)) if perm else (None, None, None)
    return Grid(n, k, q, None, p[0], p[1]), Grid(k, m, q, None, p[1], p[2])


query(AB + product_sql("a", "b"), "spgemm_plus_times")(lambda s, d: multiply.spgemm(*order_supp(s, d)))
query(G6 + product_sql("a", "b", **MIN_SQL), "spgemm_min_plus")(lambda s, d: multiply.spgemm(*succ(s, d), sr.MIN_PLUS))
query(G6 + product_sql("a", "b", "max({})", "a.v + b.v"), "spgemm_max_plus")(lambda s, d: multiply.spgemm(*succ(s, d), sr.MAX_PLUS))
query(G6 + product_sql("a", "b", "max({})", "least(a.v, b.v)"), "spgemm_max_min")(lambda s, d: multiply.spgemm(*succ(s, d), sr.MAX_MIN))
query(G6 + product_sql("a", "b", "min({})", "greatest(a.v, b.v)"), "spgemm_min_max")(lambda s, d: multiply.spgemm(*succ(s, d), sr.MIN_MAX))
query(G6 + product_sql("a", "b", "max({})", "a.v * b.v"), "spgemm_max_times")(lambda s, d: multiply.spgemm(*succ(s, d), sr.MAX_TIMES))
query(G6 + product_sql("a", "b", "count({})::BIGINT", "*"), "spgemm_count")(lambda s, d: multiply.spgemm(*succ(s, d), sr.COUNT_PAIR))
query(G6 + product_sql("a", "b", "max({})::BIGINT", "1"), "spgemm_pattern")(lambda s, d: multiply.spgemm(*succ(s, d), sr.PATTERN))


@query(G6 + product_sql("a", "b", "bool_or({})", "a.v > 1 AND b.v > 1"))
def spgemm_or_and(spark, d):
    m = succ(spark, d)[0].withColumn("v", F.col("v") > 1)
    return multiply.spgemm(m, m, sr.OR_AND)


@query(G6 + f"SELECT a.i, b.j, {bits_sql('a.j')} AS v FROM a JOIN b ON a.j = b.i GROUP BY 1, 2")
def spgemm_bit_collector(spark, d):
    m = succ(spark, d)[0]
    left = m.withColumn("v", sr.bit_of(F.col("j")))
    right = m.withColumn("v", sr.bit_of(F.col("i")))
    return multiply.spgemm(left, right, sr.bit_or())


for _hint in ("broadcast", "shuffle_hash", "merge"):
    query(AB + product_sql("a", "b"), f"op_join_{ {'broadcast': 'broadcast', 'shuffle_hash': 'shuffle_hash', 'merge': 'sort_merge'}[_hint]}")(lambda s, d, h=_hint: multiply.spgemm(*order_supp(s, d), strategy=h))

query(AB + product_sql("a", "b"), "spgemm_grid")(lambda s, d: multiply.spgemm_grid(*order_supp(s, d), *order_supp_grids(s, d)))
query(AB + product_sql("a", "b"), "spgemm_grid_permuted")(lambda s, d: multiply.spgemm_grid(*order_supp(s, d), *order_supp_grids(s, d, 3, True)))
query(AB + product_sql("a", "b"), "spgemm_rowpart")(lambda s, d: multiply.spgemm_rowpart(*order_supp(s, d), 8))
query(AB + product_sql("a", "b"), "spgemm_rowwise")(lambda s, d: multiply.spgemm_rowwise(*order_supp(s, d)))
query(AB + product_sql("a", "b"), "spgemm_generic")(lambda s, d: multiply.spgemm_generic(*order_supp(s, d)))
query(AB + product_sql("a", "b"), "spgemm_layered")(lambda s, d: multiply.spgemm_layered(*order_supp(s, d), 3))
query(G6 + product_sql("a", "b"), "spgemm_salted")(lambda s, d: multiply.spgemm_salted(*succ(s, d), heavy=3000, pieces=4))
query(f"WITH a0 AS ({drawn_sql('order_part')}), a AS (SELECT * FROM a0 WHERE u < 20000), b AS ({SQL['part_supp']}) " + product_sql("a", "b"), "spgemm_stationary_right")(lambda s, d: multiply.spgemm_stationary(drawn(s, d, "order_part").where("u < 20000"), cells(s, d, "part_supp"), keep="right"))
query(f"WITH a AS ({SQL['order_part']}), b0 AS ({drawn_sql('part_supp')}), b AS (SELECT * FROM b0 WHERE u < 20000) " + product_sql("a", "b"), "spgemm_stationary_left")(lambda s, d: multiply.spgemm_stationary(cells(s, d, "order_part"), drawn(s, d, "part_supp").where("u < 20000"), keep="left"))


def _masked(complement):
    def run(spark, d):
        m = drawn(spark, d, "user_succ")
        return multiply.spgemm_masked(m, m, m.where("u < 300000"), complement=complement)

    return run


MASKED = f"WITH a AS ({drawn_sql('user_succ')}), b AS (SELECT * FROM a), p AS ({product_sql('a', 'b')}) SELECT i, j, v FROM p {{}} JOIN (SELECT i, j FROM a WHERE u < 300000) m USING (i, j)"
query(MASKED.format("SEMI"), "spgemm_masked")(_masked(False))
query(MASKED.format("ANTI"), "spgemm_masked_complement")(_masked(True))


@query(G6 + f"SELECT i, j, sum(v)::BIGINT AS v FROM (SELECT i, j, 2 * v AS v FROM ({product_sql('a', 'b')}) UNION ALL SELECT i, j, 3 * v FROM a) GROUP BY 1, 2")
def gemm_alpha_beta(spark, d):
    m, _ = succ(spark, d)
    return multiply.gemm(2, m, m, 3, m)


for _name, _t in (("tn", (True, False)), ("nt", (False, True)), ("tt", (True, True))):
    query(G6 + product_sql("a", "b", trans=_t), f"spgemm_{_name}")(lambda s, d, t=_t: multiply.spgemm(*succ(s, d), trans=t))


@query(f"WITH a AS ({SQL['user_succ']}), b AS (SELECT * FROM a), c AS ({product_sql('a', 'b')}) " + product_sql("c", "b"))
def power3(spark, d):
    return multiply.power(succ(spark, d)[0], 3)


@query(f"WITH RECURSIVE e AS (SELECT DISTINCT i, j FROM ({SQL['user_succ']}) WHERE i < j), r AS (SELECT i, j FROM e UNION SELECT r.i, e.j FROM r JOIN e ON r.j = e.i) SELECT i, j, true AS v FROM r")
def closure_reachability(spark, d):
    m = succ(spark, d)[0].where("i < j").select("i", "j", F.lit(True).alias("v"))
    return multiply.closure(m, sr.OR_AND)


@query()
def closure_reachability_whole(spark, d):
    """closure_reachability over all edges, backward ones and loops among them."""
    m = succ(spark, d)[0].select("i", "j", F.lit(True).alias("v"))
    return multiply.closure(m, sr.OR_AND)


@query(AB + product_sql("a", "b"))
def op_sql_text(spark, d):
    a, b = order_supp(spark, d)
    return sqltext.run(spark, sqltext.spgemm_text("cells_a", "cells_b", sr.PLUS_TIMES), cells_a=a, cells_b=b)


# ---- algebraic maintenance -------------------------------------------------------------------

PREP = f"a0 AS ({drawn_sql('order_part')}), b0 AS ({drawn_sql('part_supp', 8)})"
NEW = "u BETWEEN 500000 AND 509999"
LEFT_ONLY = f"WITH {PREP}, a AS (SELECT i, j, v FROM a0 WHERE u < 510000), b AS (SELECT i, j, v FROM b0) {product_sql('a', 'b')}"
#: +5 on 1 % of the cells that are there, and 1 % new ones, in both operands.
BOTH = f"WITH {PREP}, a AS (SELECT i, j, CASE WHEN u < 10000 THEN v + 5 ELSE v END AS v FROM a0 WHERE u < 510000), b AS (SELECT i, j, CASE WHEN u < 10000 THEN v + 5 ELSE v END AS v FROM b0 WHERE u < 510000) {product_sql('a', 'b')}"


def star_of(m):
    return m.where(f"{NEW} or u < 10000").select("i", "j", F.when(F.col("u") < 10000, 5).otherwise(F.col("v")).cast("long").alias("v"))


@query(LEFT_ONLY)
def dyn_alg_insert_left(spark, d):
    a, b = drawn(spark, d, "order_part"), cells(spark, d, "part_supp")
    old = a.where("u < 500000").select("i", "j", "v")
    c = materialize(multiply.spgemm(old, b), "c")
    return alg.maintain(c, alg.delta_product(old, a.where(NEW).select("i", "j", "v"), b, None))


def _both(form):
    def run(spark, d):
        a, b = drawn(spark, d, "order_part"), drawn(spark, d, "part_supp", 8)
        a0, b0 = a.where("u < 500000").select("i", "j", "v"), b.where("u < 500000").select("i", "j", "v")
        c = materialize(multiply.spgemm(a0, b0), "c")
        return alg.maintain(c, alg.delta_product(a0, star_of(a), b0, star_of(b), form=form))

    return run


query(BOTH, "dyn_alg_both_sides")(_both("two_term"))
query(BOTH, "dyn_alg_mirrored")(_both("mirrored"))
query(BOTH, "dyn_alg_expanded")(_both("expanded"))


@query(f"WITH {PREP}, a AS (SELECT i, j, v FROM a0 WHERE u >= 10000 AND u < 500000), b AS (SELECT i, j, v FROM b0) {product_sql('a', 'b')}")
def dyn_alg_ring_delete(spark, d):
    a, b = drawn(spark, d, "order_part"), cells(spark, d, "part_supp")
    old = a.where("u < 500000").select("i", "j", "v")
    c = materialize(multiply.spgemm(old, b), "c")
    gone = a.where("u < 10000").select("i", "j", (-F.col("v")).alias("v"))
    return matrix.prune_zeros(alg.maintain(c, alg.delta_product(old, gone, b, None)))


SUCC = f"g AS ({drawn_sql('user_succ')})"
DECREASED = f"WITH {SUCC}, b AS (SELECT i, j, v FROM g), a AS (SELECT i, j, CASE WHEN u < 20000 THEN 0 ELSE v END AS v FROM g WHERE u < 520000) "


@query(DECREASED + product_sql("a", "b", **MIN_SQL))
def dyn_alg_minplus_decrease(spark, d):
    g = drawn(spark, d, "user_succ")
    b, old = g.select("i", "j", "v"), g.where("u < 500000").select("i", "j", "v")
    c = materialize(multiply.spgemm(old, b, sr.MIN_PLUS), "c")
    star = g.where("u < 20000 or u between 500000 and 519999").select("i", "j", F.when(F.col("u") < 20000, 0).otherwise(F.col("v")).cast("long").alias("v"))
    return alg.maintain(c, alg.delta_product(old, star, b, None, sr.MIN_PLUS), sr.MIN_PLUS)


@query(f"WITH {SUCC}, b AS (SELECT i, j, v FROM g), a AS (SELECT i, j, v FROM g WHERE u < 200000) {product_sql('a', 'b')}")
def dyn_alg_ten_batches(spark, d):
    g = drawn(spark, d, "user_succ")
    b = g.select("i", "j", "v")
    view = ProductView.create(matrix.empty(spark), b, bits=False)
    for k in range(10):
        view.update(updates.UpdateBatch.build(g.where(f"u >= {k * 20000} and u < {(k + 1) * 20000}").select("i", "j", "v", F.lit("add").alias("op")), k), batch_id=k, method="algebraic")
    return view.result()


def _alg_trans(t):
    def run(spark, d):
        g, h = drawn(spark, d, "user_succ"), drawn(spark, d, "user_succ", 8)
        old = lambda m: m.where("u < 500000").select("i", "j", "v")
        star = lambda m: m.where("u between 500000 and 519999").select("i", "j", "v")
        c = materialize(multiply.spgemm(old(g), old(h), trans=t), "c")
        return alg.maintain(c, alg.delta_product(old(g), star(g), old(h), star(h), trans=t))

    return run


for _name, _t in (("tn", (True, False)), ("nt", (False, True)), ("tt", (True, True))):
    query(f"WITH {SUCC}, h AS ({drawn_sql('user_succ', 8)}), a AS (SELECT * FROM g WHERE u < 520000), b AS (SELECT * FROM h WHERE u < 520000) " + product_sql("a", "b", trans=_t), f"dyn_alg_transposed_{_name}")(_alg_trans(_t))

#: What the grid's rounds produce: the product of the deltas' terms, from scratch as a difference of products.
ROUNDS = f"""WITH {PREP}, ao AS (SELECT i, j, v FROM a0 WHERE u < 500000), an AS (SELECT i, j, CASE WHEN u < 10000 THEN v + 5 ELSE v END AS v FROM a0 WHERE u < 510000),
bo AS (SELECT i, j, v FROM b0 WHERE u < 500000), bn AS (SELECT i, j, CASE WHEN u < 10000 THEN v + 5 ELSE v END AS v FROM b0 WHERE u < 510000),
cn AS ({product_sql('an', 'bn')}), co AS ({product_sql('ao', 'bo')})
SELECT i, j, (cn.v - coalesce(co.v, 0))::BIGINT AS v FROM cn LEFT JOIN co USING (i, j) WHERE cn.v <> coalesce(co.v, 0)"""


@query(ROUNDS)
def dyn_alg_rounds_sim(spark, d):
    a, b = drawn(spark, d, "order_part"), drawn(spark, d, "part_supp", 8)
    a0, b0 = a.where("u < 500000").select("i", "j", "v"), b.where("u < 500000").select("i", "j", "v")
    b_new = updates.apply_add(b0, star_of(b))
    return alg.simulate_rounds(a0, star_of(a), b_new, star_of(b), *order_supp_grids(spark, d, 4, True))[0]


@query(BOTH)
def dyn_alg_view(spark, d):
    a, b = drawn(spark, d, "order_part"), drawn(spark, d, "part_supp", 8)
    view = ProductView.create(a.where("u < 500000"), b.where("u < 500000"))
    batch = lambda m: updates.UpdateBatch.build(star_of(m).withColumn("op", F.lit("add")))
    view.update(batch(a), batch(b), batch_id=0, method="algebraic")
    return view.result()


def batch_sql(name: str, as_: str, seed: int = 7, t: int = 10_000) -> str:
    return f"{as_}0 AS ({drawn_sql(name, seed)}), {as_}old AS (SELECT i, j, v FROM {as_}0 WHERE u < 500000), {as_} AS (SELECT i, j, CASE WHEN u < {2 * t} THEN v + 100 ELSE v END AS v FROM {as_}0 WHERE u >= {t} AND u < {500_000 + t}), {as_}star AS (SELECT i, j FROM {as_}0 WHERE u < {2 * t} OR (u >= 500000 AND u < {500_000 + t}))"


#: (+, ·) over numbers that know no subtraction: neither a ring nor idempotent.
NAT = sr.Semiring.define("nat", F.sum, lambda a, b: a + b, lambda a, b: a * b, 0, 1)


@query(f"WITH {SUCC}, b AS (SELECT i, j, CASE WHEN u < 10000 THEN v + 3 ELSE v END AS v FROM g), a AS (SELECT i, j, CASE WHEN u < 20000 THEN v + 2 ELSE v END AS v FROM g WHERE u < 520000) {product_sql('a', 'b')}")
def dyn_alg_nat_add(spark, d):
    """Adds to cells that are there, insertions, and sets that change nothing, without subtraction."""
    g = drawn(spark, d, "user_succ")
    view = ProductView.create(g.where("u < 500000"), g, NAT)
    op = F.when(F.col("u") < 20000, "add").otherwise("set").alias("op")
    left = g.where("u < 30000 or u between 500000 and 519999").select("i", "j", F.when(F.col("u") < 20000, 2).otherwise(F.col("v")).cast("long").alias("v"), op)
    right = g.where("u < 10000").select("i", "j", F.lit(3).cast("long").alias("v"), F.lit("add").alias("op"))
    view.update(updates.UpdateBatch.build(left), updates.UpdateBatch.build(right), batch_id=0, method="algebraic")
    return view.result()


def _stored(spark, d, s=sr.PLUS_TIMES) -> StoredProduct:
    a, b = drawn(spark, d, "order_part"), drawn(spark, d, "part_supp", 8)
    dims = inst.dims(spark, d, ("orders", "o_orderkey"), ("part", "p_partkey"), ("supplier", "s_suppkey"))
    view = StoredProduct.create(a.where("u < 500000"), b.where("u < 500000"), dims, new_path(spark, "product"), s, q=2)
    batch = lambda m: updates.UpdateBatch.build(star_of(m).withColumn("op", F.lit("add")))
    view.update(batch(a), batch(b), batch_id=0)
    return view


@query(BOTH)
def dyn_view_blocks(spark, d):
    """Operands and product on block stores, both operands changed by additions."""
    return _stored(spark, d).result()


@query(f"WITH {batch_sql('user_succ', 'a')}, {batch_sql('user_succ', 'b', 8)} " + product_sql("a", "b", "min({})", "a.v + b.v", more=", " + bits_sql("{k}") + " AS bits"))
def dyn_view_blocks_general(spark, d):
    """Deletions, raises and insertions in both operands on block stores; the fingerprints follow."""
    g, h = drawn(spark, d, "user_succ"), drawn(spark, d, "user_succ", 8)
    n = inst.dims(spark, d, ("events", "user_id"))[0]
    view = StoredProduct.create(g.where("u < 500000"), h.where("u < 500000"), (n, n, n), new_path(spark, "product"), sr.MIN_PLUS, q=2)

    def batch(m):
        kind = F.when(F.col("u") < 10_000, "del").otherwise("set")
        value = F.when(F.col("u") < 20_000, F.col("v") + 100).otherwise(F.col("v"))
        return updates.UpdateBatch.build(m.where("u < 20000 or u >= 500000 and u < 510000").select("i", "j", value.alias("v"), kind.alias("op")))

    if view.update(batch(g), batch(h), batch_id=0) != "general":
        raise AssertionError("the batch deletes")
    return view.c.current()


@query(LEFT_ONLY)
def baseline_delta_static(spark, d):
    a, b = drawn(spark, d, "order_part"), cells(spark, d, "part_supp")
    c = materialize(multiply.spgemm(a.where("u < 500000"), b), "c")
    return baselines.delta_static(c, a.where(NEW).select("i", "j", "v"), b, order_supp_grids(spark, d))


@query(LEFT_ONLY)
def baseline_recompute(spark, d):
    a, b = drawn(spark, d, "order_part"), cells(spark, d, "part_supp")
    return baselines.recompute(a.where("u < 510000").select("i", "j", "v"), b, grids=order_supp_grids(spark, d))


@query(SQL["part_supp"])
def baseline_static_dcsr(spark, d):
    from deltamat.operators.layout import from_dcsr
    from deltamat.queries.matrices import part_supp_grid

    return from_dcsr(baselines.static_dcsr(inst.part_supp(spark, d), part_supp_grid(spark, d)))


# ---- general maintenance ---------------------------------------------------------------------

BITS = ", " + bits_sql("{k}") + " AS bits"


def bits_more(ell: int = 64) -> str:
    return ", " + bits_sql("{k}", ell) + " AS bits"


@query(G6 + product_sql("a", "b", **MIN_SQL, more=BITS))
def bits_product(spark, d):
    return gen.product_with_bits(*succ(spark, d), sr.MIN_PLUS)


class Batch:
    """A general batch on one operand: below ``t`` deleted, below 2t raised by 100, t new ones."""

    def __init__(self, spark, d, name: str, seed: int = 7, t: int = 10_000):
        m = drawn(spark, d, name, seed)
        self.old = materialize(m.where("u < 500000").select("i", "j", "v"), "old")
        raised = F.when(F.col("u") < 2 * t, F.col("v") + 100).otherwise(F.col("v")).alias("v")
        self.new = materialize(m.where(f"u >= {t} and u < {500_000 + t}").select("i", "j", raised), "new")
        self.star = materialize(m.where(f"u < {2 * t} or u >= 500000 and u < {500_000 + t}").select("i", "j"), "star")


#: part × order times order × customer: long rows, where fingerprints pay.
SPARSE = ("part_order", "order_cust")
SPARSE_SQL = f"WITH {batch_sql('part_order', 'a')}, b AS ({SQL['order_cust']})"
PATTERN_SQL = f"{SPARSE_SQL}, star AS (SELECT s.i, b.j, {bits_sql('s.j')} AS bits FROM astar s JOIN b ON s.j = b.i GROUP BY 1, 2)"
OLD_BITS = product_sql("aold", "b", **MIN_SQL, more=BITS)
ROW_BITS = f"{PATTERN_SQL}, c AS ({OLD_BITS}), e AS (SELECT s.i, s.j, s.bits | coalesce(c.bits, 0) AS bits FROM star s LEFT JOIN c USING (i, j)), r AS (SELECT i, bit_or(bits) AS bits FROM e GROUP BY 1)"


def sparse_steps(spark, d, **more) -> gen.Steps:
    x, b = Batch(spark, d, SPARSE[0]), cells(spark, d, SPARSE[1])
    c = materialize(gen.product_with_bits(x.old, b, sr.MIN_PLUS, more.get("ell", 64)), "c")
    return gen.maintain_general(c, x.old, x.new, x.star, b, None, sr.MIN_PLUS, **more)


query(f"{PATTERN_SQL} SELECT * FROM star", "bits_pattern")(lambda s, d: sparse_steps(s, d).pattern)
query(f"{ROW_BITS} SELECT * FROM e", "bits_needed_E")(lambda s, d: sparse_steps(s, d).needed)
query(f"{ROW_BITS} SELECT * FROM r", "bits_row_R")(lambda s, d: sparse_steps(s, d).rows)
query(f"{ROW_BITS} SELECT a.i, a.j, a.v FROM a JOIN r USING (i) WHERE (CASE WHEN r.bits < 0 THEN r.bits::HUGEINT + 18446744073709551616 ELSE r.bits::HUGEINT END // (1::UBIGINT << (a.j % 64)::INT)::HUGEINT) % 2 = 1", "bits_filtered_left")(lambda s, d: sparse_steps(s, d).filtered)

FRESH = f"{SPARSE_SQL} {product_sql('a', 'b', **MIN_SQL)}"
for _name, _more in {
    "dyn_gen_left": {},
    "dyn_gen_rows_only": {"variant": "none"},
    "dyn_gen_row_bits": {"variant": "rows"},
    "dyn_gen_exact": {"variant": "exact"},
    "dyn_gen_right_filter": {"side": "right"},
    "dyn_gen_ell8": {"ell": 8},
    "dyn_gen_ell16": {"ell": 16},
    "dyn_gen_ell32": {"ell": 32},
    "dyn_gen_ell62": {"ell": 62},
}.items():
    query(FRESH, _name)(lambda s, d, m=_more: sparse_steps(s, d, **m).result.select("i", "j", "v"))
query(f"{SPARSE_SQL} {product_sql('a', 'b', **MIN_SQL, more=BITS)}", "dyn_gen_bits_maintained")(lambda s, d: sparse_steps(s, d).result)

TWO = f"WITH {batch_sql('user_succ', 'a')}, {batch_sql('user_succ', 'b', 8)} "


def two_sided(spark, d, trans=(False, False), s=sr.MIN_PLUS, **more) -> gen.Steps:
    x, y = Batch(spark, d, "user_succ"), Batch(spark, d, "user_succ", 8)
    c = materialize(gen.product_with_bits(x.old, y.old, s, trans=trans), "c")
    return gen.maintain_general(c, x.old, x.new, x.star, y.new, y.star, s, trans=trans, **more)


query(TWO + product_sql("a", "b", **MIN_SQL, more=BITS), "dyn_gen_mixed_both_sides")(lambda s, d: two_sided(s, d).result)
query(TWO + product_sql("a", "b", more=BITS), "dyn_gen_plus_times")(lambda s, d: two_sided(s, d, s=sr.PLUS_TIMES).result)
for _name, _t in (("tn", (True, False)), ("nt", (False, True)), ("tt", (True, True))):
    query(TWO + product_sql("a", "b", **MIN_SQL, trans=_t), f"dyn_gen_transposed_{_name}")(lambda s, d, t=_t: two_sided(s, d, t).result.select("i", "j", "v"))
    query(TWO + product_sql("a", "b", **MIN_SQL, trans=_t), f"dyn_gen_transposed_{_name}_right")(lambda s, d, t=_t: two_sided(s, d, t, side="right").result.select("i", "j", "v"))


def _one_kind(keep: str, change):
    def run(spark, d):
        g = drawn(spark, d, "user_succ")
        b, old = cells(spark, d, "user_succ"), g.where("u < 500000").select("i", "j", "v")
        c = materialize(gen.product_with_bits(old, b, sr.MIN_PLUS), "c")
        new = g.where("u < 500000").where(keep).select("i", "j", change.alias("v"))
        return gen.maintain_general(c, old, new, g.where("u < 20000").select("i", "j"), b, None, sr.MIN_PLUS).result.select("i", "j", "v")

    return run


query(f"WITH {SUCC}, b AS (SELECT i, j, v FROM g), a AS (SELECT i, j, CASE WHEN u < 20000 THEN v + 100 ELSE v END AS v FROM g WHERE u < 500000) {product_sql('a', 'b', **MIN_SQL)}", "dyn_gen_raise")(lambda s, d: _one_kind("true", F.expr("CASE WHEN u < 20000 THEN v + 100 ELSE v END"))(s, d))
query(f"WITH {SUCC}, b AS (SELECT i, j, v FROM g), a AS (SELECT i, j, v FROM g WHERE u >= 20000 AND u < 500000) {product_sql('a', 'b', **MIN_SQL)}", "dyn_gen_delete")(lambda s, d: _one_kind("u >= 20000", F.col("v"))(s, d))


@query(f"WITH {SUCC}, b AS (SELECT i, j FROM g), a AS (SELECT i, j FROM g WHERE u >= 20000 AND u < 500000) SELECT DISTINCT a.i, b.j, true AS v FROM a JOIN b ON a.j = b.i")
def dyn_gen_bool_delete(spark, d):
    g = drawn(spark, d, "user_succ").withColumn("v", F.lit(True))
    b, old = g.select("i", "j", "v"), g.where("u < 500000").select("i", "j", "v")
    c = materialize(gen.product_with_bits(old, b, sr.OR_AND), "c")
    steps = gen.maintain_general(c, old, old.join(g.where("u < 20000"), ["i", "j"], "left_anti"), g.where("u < 20000").select("i", "j"), b, None, sr.OR_AND)
    return steps.result.select("i", "j", "v")


#: Batch k deletes the cells of slice k, raises those of slice k + 10 and inserts slice k above the half.
TEN = f"WITH {SUCC}, b AS (SELECT i, j, v FROM g), a AS (SELECT i, j, CASE WHEN u >= 30000 AND u < 60000 THEN v + 100 ELSE v END AS v FROM g WHERE u >= 30000 AND u < 530000) "


@query(TEN + product_sql("a", "b", **MIN_SQL, more=BITS))
def dyn_gen_ten_batches(spark, d):
    g = drawn(spark, d, "user_succ")
    view = ProductView.create(g.where("u < 500000"), cells(spark, d, "user_succ"), sr.MIN_PLUS)
    for k in range(10):
        part = lambda lo, k=k: (F.col("u") >= lo + 3000 * k) & (F.col("u") < lo + 3000 * (k + 1))
        rows = g.where(part(0)).select("i", "j", "v", F.lit("del").alias("op"))
        rows = rows.unionByName(g.where(part(30_000)).select("i", "j", (F.col("v") + 100).alias("v"), F.lit("set").alias("op")))
        rows = rows.unionByName(g.where(part(500_000)).select("i", "j", "v", F.lit("set").alias("op")))
        view.update(updates.UpdateBatch.build(rows, k), batch_id=k, method="general")
    return view.c.select("i", "j", "v", "bits")


@query(DECREASED.replace("THEN 0 ELSE v END AS v FROM g WHERE u < 520000)", "THEN 0 ELSE v END AS v FROM g WHERE u < 520000 AND u >= 10000)") + product_sql("a", "b", **MIN_SQL, more=BITS))
def dyn_mixed_history(spark, d):
    """An algebraic batch, then a general one on what it left: the fingerprints must have followed."""
    g = drawn(spark, d, "user_succ")
    view = ProductView.create(g.where("u < 500000"), cells(spark, d, "user_succ"), sr.MIN_PLUS)
    lower = g.where("u < 20000 or u between 500000 and 519999").select("i", "j", F.when(F.col("u") < 20000, 0).otherwise(F.col("v")).cast("long").alias("v"), F.lit("set").alias("op"))
    view.update(updates.UpdateBatch.build(lower, 0), batch_id=0, method="algebraic")
    view.update(updates.UpdateBatch.build(g.where("u < 10000").select("i", "j", "v", F.lit("del").alias("op")), 1), batch_id=1, method="general")
    return view.c.select("i", "j", "v", "bits")


def flagship(spark, d):
    """Half of order × part times part × supplier, then 1 % of insertions."""
    a, b = drawn(spark, d, "order_part"), cells(spark, d, "part_supp")
    view = ProductView.create(a.where("u < 500000"), b)
    view.update(updates.UpdateBatch.build(a.where(NEW).select("i", "j", "v")), batch_id=0)
    return view.result()


query(LEFT_ONLY, "flagship")(flagship)
