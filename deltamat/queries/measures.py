"""Counts of work and movement, and the applications."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamat.functions import semiring as sr
from deltamat.operators import dynamic_algebraic as alg
from deltamat.operators import graphs, matrix, multiply, updates
from deltamat.operators.layout import Grid
from deltamat.plans import cost
from deltamat.plans.planner import choose, term_count
from deltamat.plans.view import ProductView
from deltamat.queries.base import SQL, cells, drawn, drawn_sql, product_sql, query
from deltamat.queries.products import AB, G6, PATTERN_SQL, ROW_BITS, SUCC, order_supp, order_supp_grids, sparse_steps, succ
from deltamat.sources import instances as inst
from deltamat.sources.scratch import materialize


@query(AB + "SELECT sum(x * y)::BIGINT AS flops FROM (SELECT j AS k, count(*) AS x FROM a GROUP BY 1) JOIN (SELECT i AS k, count(*) AS y FROM b GROUP BY 1) USING (k)")
def cost_flops(spark, d):
    return cost.flops(*order_supp(spark, d))


@query(G6 + f"SELECT (SELECT count(*) FROM a JOIN b ON a.j = b.i)::BIGINT AS flops, count(*)::BIGINT AS nnz_c, round((SELECT count(*) FROM a JOIN b ON a.j = b.i) / count(*), 6)::DOUBLE AS factor FROM ({product_sql('a', 'b')})")
def cost_compression(spark, d):
    m, _ = succ(spark, d)
    return cost.compression(m, m, sr.PLUS_TIMES)


Q = 4
#: An insert-only batch on the left operand: what the grid moves for it by each method.
FRACTIONS = (100, 1000, 10_000, 100_000, 500_000)


def volumes(spark, d, parts: int):
    a, b = drawn(spark, d, "order_part"), cells(spark, d, "part_supp")
    star = materialize(a.where(f"u < {parts}").select("i", "j", "v"), "star")
    ga, gb = order_supp_grids(spark, d, Q, True)
    rounds = alg.simulate_rounds(a, star, b, matrix.empty(spark), ga, gb)[1]
    dynamic = rounds.agg(F.sum("cells").cast("long").alias("dynamic"))
    full = cost.volume_static(a, b, Q).select(F.col("cells").alias("static_full"))
    delta = cost.volume_static(star, b, Q).select(F.col("cells").alias("static_delta"))
    return dynamic.crossJoin(full).crossJoin(delta).select(F.lit(parts).cast("long").alias("parts"), "dynamic", "static_full", "static_delta")  # single rows


def volumes_sql(parts: int) -> str:
    p = lambda x, n: f"floor((({x} * 7919 + 13) % {n}) * 4 / {n})"
    return f"""SELECT {parts}::BIGINT AS parts,
((SELECT count(*) FROM s, dims WHERE {p('i', 'n')} <> {p('j', 'k')}) + 3 * (SELECT count(*) FROM s) + (SELECT count(*) FROM (SELECT DISTINCT s.i, b.j, {p('b.i', 'k')} AS pi, {p('s.i', 'n')} AS oi FROM s JOIN b ON s.j = b.i, dims) WHERE pi <> oi))::BIGINT AS dynamic,
(3 * ((SELECT count(*) FROM a) + (SELECT count(*) FROM b)))::BIGINT AS static_full, (3 * ((SELECT count(*) FROM s) + (SELECT count(*) FROM b)))::BIGINT AS static_delta""".replace("FROM s,", f"FROM (SELECT * FROM a WHERE u < {parts}) s,").replace("FROM s)", f"FROM a WHERE u < {parts})").replace("FROM s JOIN", f"FROM (SELECT * FROM a WHERE u < {parts}) s JOIN")


VOLUMES = f"WITH a AS ({drawn_sql('order_part')}), b AS ({SQL['part_supp']}), dims AS (SELECT (SELECT max(o_orderkey) + 1 FROM orders) AS n, (SELECT max(p_partkey) + 1 FROM part) AS k) "
query(VOLUMES + volumes_sql(10_000), "cost_comm_static_vs_dynamic")(lambda s, d: volumes(s, d, 10_000))


@query(VOLUMES + " UNION ALL ".join(volumes_sql(p) for p in FRACTIONS))
def cost_crossover_sweep(spark, d):
    out = volumes(spark, d, FRACTIONS[0])
    for p in FRACTIONS[1:]:
        out = out.unionByName(volumes(spark, d, p))
    return out


EFFECT = f"""{PATTERN_SQL}, c AS (SELECT a.i, b.j, bit_or(1::UBIGINT << (a.j % 64)::INT) AS bits FROM aold a JOIN b ON a.j = b.i GROUP BY 1, 2),
u AS (SELECT s.i, b.j, bit_or(1::UBIGINT << (s.j % 64)::INT) AS bits FROM astar s JOIN b ON s.j = b.i GROUP BY 1, 2),
r AS (SELECT u.i, bit_or(u.bits | coalesce(c.bits, 0)) AS bits FROM u LEFT JOIN c USING (i, j) GROUP BY 1)
SELECT (SELECT count(*) FROM a)::BIGINT AS all_cells, (SELECT count(*) FROM a WHERE i IN (SELECT i FROM star))::BIGINT AS rows_only,
(SELECT count(*) FROM a JOIN r USING (i) WHERE (r.bits & (1::UBIGINT << (a.j % 64)::INT)) <> 0)::BIGINT AS filtered,
(SELECT count(*) FROM (SELECT DISTINCT a.i, a.j FROM a JOIN b ON a.j = b.i JOIN star ON star.i = a.i AND star.j = b.j))::BIGINT AS exact"""


@query(EFFECT)
def cost_filter_effect(spark, d):
    from deltamat.queries.products import Batch

    steps = sparse_steps(spark, d)
    x = Batch(spark, d, "part_order")
    return cost.filter_effect(x.new, cells(spark, d, "order_cust"), steps.pattern, steps.rows)


FILTERED = "ar AS (SELECT a.i, a.j, a.v FROM a JOIN r USING (i) WHERE (CASE WHEN r.bits < 0 THEN r.bits::HUGEINT + 18446744073709551616 ELSE r.bits::HUGEINT END // (1::UBIGINT << (a.j % 64)::INT)::HUGEINT) % 2 = 1)"
COMM = f"""{ROW_BITS}, {FILTERED}, dims AS (SELECT (SELECT max(p_partkey) + 1 FROM part) AS n, (SELECT max(o_orderkey) + 1 FROM orders) AS k),
z AS (SELECT DISTINCT floor(b.i * 4 / k) AS pi, ar.i, b.j, floor(ar.i * 4 / n) AS bi FROM ar JOIN b ON ar.j = b.i JOIN star ON star.i = ar.i AND star.j = b.j, dims)
SELECT 'transposed_send' AS step, (SELECT count(*) FROM ar, dims WHERE floor(ar.i * 4 / n) <> floor(ar.j * 4 / k))::BIGINT AS cells
UNION ALL SELECT 'broadcast', (3 * ((SELECT count(*) FROM ar) + (SELECT count(*) FROM star)))::BIGINT
UNION ALL SELECT 'reduce', (SELECT count(*) FROM z WHERE pi <> bi)::BIGINT"""


@query(COMM)
def cost_comm_general(spark, d):
    steps, b = sparse_steps(spark, d), cells(spark, d, "order_cust")
    n, k, m = inst.dims(spark, d, ("part", "p_partkey"), ("orders", "o_orderkey"), ("customer", "c_custkey"))
    ga, gb = Grid(n, k, Q), Grid(k, m, Q)
    return cost.volume_general(steps.filtered, steps.pattern, cost.general_partials(steps.filtered, b, steps.pattern, gb), ga, gb)


#: Counts of order × customer times customer × nation with 1 % of the left cells changed.
BOUNDS_AT = f"""WITH a AS ({drawn_sql('order_cust')}), b AS ({SQL['cust_nation']}), s AS (SELECT i, j FROM a WHERE u < 10000), cs AS (SELECT DISTINCT s.i, b.j FROM s JOIN b ON s.j = b.i), ar AS (SELECT i, j FROM a WHERE i IN (SELECT i FROM cs)),
n AS (SELECT (SELECT count(*) FROM a) AS na, (SELECT count(*) FROM b) AS nb, (SELECT count(*) FROM (SELECT DISTINCT a.i, b.j FROM a JOIN b ON a.j = b.i)) AS nc, (SELECT count(*) FROM s) AS ns, (SELECT count(*) FROM cs) AS ncs, (SELECT count(*) FROM ar) AS nar,
(SELECT count(*) FROM a JOIN b ON a.j = b.i) AS f, (SELECT count(*) FROM s JOIN b ON s.j = b.i) AS fd, (SELECT count(*) FROM ar JOIN b ON ar.j = b.i) AS fg)"""


@query(
    BOUNDS_AT + " SELECT 'redistribution' AS method, 8.0::DOUBLE AS latency, (ns / 64)::DOUBLE AS bandwidth, (ns / 64 + 8)::DOUBLE AS work, (ns / 64)::DOUBLE AS memory FROM n UNION ALL SELECT 'static', 48, (na + nb) / 8, f / 64, greatest(na, nb, nc) / 64 FROM n "
    "UNION ALL SELECT 'algebraic', 48, greatest(ns, ncs) / 8, fd * 6 / 64, greatest(na, nb, nc) / 64 FROM n UNION ALL SELECT 'general', 48, (nar + ncs) / 8, fg * 6 / 64, greatest(na, nb, nc) / 64 FROM n"
)
def cost_bounds(spark, d):
    """The bounds at the counts of a product on the given tables, all taken by Spark."""
    a, b = drawn(spark, d, "order_cust"), cells(spark, d, "cust_nation")
    star = a.where("u < 10000").select("i", "j", "v")
    c_star = multiply.spgemm(star, b).select("i", "j")
    a_r = a.select("i", "j", "v").join(c_star.select("i").distinct(), "i", "left_semi")
    counts = {"a": a, "b": b, "c": multiply.spgemm(a, b), "a_star": star, "b_star": matrix.empty(spark), "c_star": c_star, "a_r": a_r}
    terms = {"flops": a, "flops_delta": star, "flops_general": a_r}
    return cost.bounds(spark, {k: m.count() for k, m in counts.items()} | {k: term_count(m, b) for k, m in terms.items()}, 64)


#: The planner's prices from exact counts: cells moved and terms for each process of an 8 x 8 grid.
CHOICES = f"""WITH a AS ({drawn_sql('order_part')}), b AS ({SQL['part_supp']}), deg AS (SELECT i, count(*) AS e FROM b GROUP BY 1), t AS (SELECT a.u, coalesce(e, 0) AS e FROM a LEFT JOIN deg ON a.j = deg.i),
parts AS (SELECT unnest([{', '.join(map(str, FRACTIONS))}])::BIGINT AS parts),
n AS (SELECT parts, (SELECT count(*) FROM a) AS na, (SELECT count(*) FROM b) AS nb, (SELECT sum(e) FROM t) AS f, (SELECT count(*) FROM t WHERE u < parts) AS st, (SELECT coalesce(sum(e), 0) FROM t WHERE u < parts) AS fd FROM parts),
c AS (SELECT *, 7 * (na + nb) + f / 64 AS recompute, 8 * st + fd + fd / 64 AS algebraic, 7 * (st + nb) + fd / 64 AS delta_static, na * least(1.0, fd / 64) AS needed FROM n),
g AS (SELECT *, algebraic + 7 * (needed + fd) + needed * (f / na) / 64 AS general FROM c)
SELECT parts, 'algebraic' AS kind, CASE WHEN st = 0 THEN 'none' WHEN recompute <= algebraic AND recompute <= delta_static THEN 'recompute' WHEN algebraic <= delta_static THEN 'algebraic' ELSE 'delta_static' END AS method,
CASE WHEN st = 0 THEN 'none' WHEN algebraic < recompute AND algebraic <= delta_static THEN CASE WHEN st <= 1000000 THEN 'broadcast' ELSE 'shuffle_delta' END ELSE 'grid' END AS tier FROM g
UNION ALL SELECT parts, 'general', CASE WHEN st = 0 THEN 'none' WHEN recompute <= general THEN 'recompute' ELSE 'general' END,
CASE WHEN st = 0 THEN 'none' WHEN recompute <= general THEN 'grid' WHEN st + needed <= 1000000 THEN 'broadcast' ELSE 'shuffle_delta' END FROM g"""


@query(CHOICES)
def planner_choices(spark, d):
    """Which way the planner goes as the batch grows, from exact counts."""
    a, b = drawn(spark, d, "order_part"), cells(spark, d, "part_supp")
    n = {"a": a.count(), "b": b.count(), "c": 1_000_000, "b_star": 0, "flops": term_count(a, b)}
    rows = []
    for parts in FRACTIONS:
        star = a.where(f"u < {parts}")
        m = n | {"a_star": star.count(), "flops_delta": term_count(star, b)}
        for kind in ("algebraic", "general"):
            p = choose(m, kind)
            rows.append((parts, kind, p.method, p.tier))
    return spark.createDataFrame(rows, "parts long, kind string, method string, tier string")


@query(AB + "SELECT (SELECT count(*) FROM a JOIN b ON a.j = b.i)::BIGINT AS flops, (SELECT count(*) FROM (SELECT DISTINCT a.i, b.j FROM a JOIN b ON a.j = b.i)) <= least((SELECT count(*) FROM a JOIN b ON a.j = b.i), (SELECT (max(o_orderkey) + 1) FROM orders) * (SELECT max(s_suppkey) + 1 FROM supplier)) AS bounded")
def cost_estimate(spark, d):
    """The scalar products of a product before it is run, and whether the estimate bounds its cells."""
    a, b = order_supp(spark, d)
    n, m = inst.dims(spark, d, ("orders", "o_orderkey"), ("supplier", "s_suppkey"))
    flops, most = multiply.estimate(a, b, n, m)
    size = multiply.spgemm(a, b).agg(F.count("*").alias("n"))
    return size.select(F.lit(flops).cast("long").alias("flops"), (F.col("n") <= most).alias("bounded"))


# ---- applications ----------------------------------------------------------------------------

UNDIRECTED = f"WITH g AS ({SQL['user_succ']}), e AS (SELECT DISTINCT least(i, j) AS i, greatest(i, j) AS j FROM g WHERE i <> j) "


@query(UNDIRECTED + "SELECT count(*)::BIGINT AS triangles FROM e x JOIN e y ON x.j = y.i JOIN e z ON z.i = x.i AND z.j = y.j")
def app_triangles(spark, d):
    return graphs.triangles(succ(spark, d)[0])


START = "SELECT i, i AS j, 0::BIGINT AS v FROM (SELECT DISTINCT i FROM g)"


@query(
    f"WITH g AS ({SQL['user_succ']}), p0 AS ({START}), " + ", ".join(f"p{k} AS (SELECT i, j, min(v) AS v FROM (SELECT * FROM p{k - 1} UNION ALL SELECT p.i, g.j, p.v + g.v FROM p{k - 1} p JOIN g ON p.j = g.i) GROUP BY 1, 2)" for k in (1, 2, 3)) + " SELECT i, j, v FROM p3"
)
def app_sssp_hops3(spark, d):
    m, _ = succ(spark, d)
    return graphs.shortest_paths(m, m.select("i").distinct(), 3)


@query(f"WITH RECURSIVE g AS (SELECT * FROM ({SQL['user_succ']}) WHERE i <> j AND v > 1), r AS (SELECT DISTINCT i, i AS j, 0::BIGINT AS v FROM g UNION SELECT r.i, g.j, r.v + 1 FROM r JOIN g ON r.j = g.i WHERE r.v < 6) SELECT i, j, min(v) AS v FROM r GROUP BY 1, 2")
def app_bfs_levels(spark, d):
    m = succ(spark, d)[0].where("v > 1")
    return graphs.bfs(m, m.where("i <> j").select("i").distinct(), 6)


@query()
def app_bfs_levels_whole(spark, d):
    """app_bfs_levels over all edges, those seen once among them."""
    m = succ(spark, d)[0]
    return graphs.bfs(m, m.where("i <> j").select("i").distinct(), 6)


@query(f"WITH a AS (SELECT i, j, v FROM ({SQL['order_part']})), s AS ({SQL['cust_nation']}) SELECT c.n AS i, a.j % 10 AS j, sum(a.v)::BIGINT AS v FROM a JOIN (SELECT o_orderkey AS i, c_nationkey::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey) c USING (i) GROUP BY 1, 2")
def app_contract_nation(spark, d):
    orders = inst.read(spark, d, "orders").join(inst.read(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).select(F.col("o_orderkey").alias("i"), F.col("c_nationkey").cast("long").alias("j"), F.lit(1).cast("long").alias("v"))
    parts = inst.read(spark, d, "part").select(F.col("p_partkey").alias("i"), (F.col("p_partkey") % 10).alias("j"), F.lit(1).cast("long").alias("v"))
    return graphs.contract(cells(spark, d, "order_part"), orders, parts)


@query(f"WITH x AS (SELECT vec_id::BIGINT AS i, (generate_subscripts(embedding, 1) - 1)::BIGINT AS j, unnest(embedding) AS e FROM embeddings), m AS (SELECT i, j, round(e::DOUBLE * 1000)::BIGINT AS v FROM x WHERE e > 0.2), l AS ({SQL['vec_label']}) SELECT l.j AS i, m.j, sum(m.v)::BIGINT AS v FROM l JOIN m ON l.i = m.i GROUP BY 1, 2")
def app_contract_label(spark, d):
    return multiply.spgemm(cells(spark, d, "vec_label"), inst.vec_dim(spark, d, 0.2), trans=(True, False))


@query(
    f"WITH g AS ({SQL['user_succ']}), f AS (SELECT i, j, v / sum(v) OVER (PARTITION BY j) AS v FROM g), s AS (SELECT a.i, b.j, pow(sum(a.v * b.v), 2) AS v FROM f a JOIN f b ON a.j = b.i GROUP BY 1, 2), n AS (SELECT i, j, v / sum(v) OVER (PARTITION BY j) AS v FROM s) "
    "SELECT i, j, round(v, 6) AS v FROM n WHERE v >= 0.0101234"
)
def app_cluster_step(spark, d):
    return matrix.apply(graphs.cluster_step(succ(spark, d)[0], 2, 0.0101234), lambda v: F.round(v, 6))


@query(f"WITH a AS ({SQL['order_part']}), b AS ({SQL['part_supp']}), p AS (SELECT a.i, b.j % 7 AS j, sum(a.v * b.v) AS v FROM a JOIN (SELECT i, j % 7 AS j, sum(v) AS v FROM b GROUP BY 1, 2) b ON a.j = b.i GROUP BY 1, 2) SELECT i, j, (v - 3000)::BIGINT AS v FROM p WHERE v > 3000")
def app_dnn_layer(spark, d):
    a, b = order_supp(spark, d)
    weights = b.groupBy("i", (F.col("j") % 7).alias("j")).agg(F.sum("v").alias("v"))
    return graphs.dnn_layer(a, weights, -3000)


@query(f"WITH s AS ({SQL['supp_nation']}), b AS ({SQL['part_supp']}), a AS ({SQL['order_part']}) SELECT x.i, s.j, sum(x.v * s.v)::BIGINT AS v FROM (SELECT a.i, b.j, sum(a.v * b.v) AS v FROM a JOIN b ON a.j = b.i GROUP BY 1, 2) x JOIN s ON x.j = s.i GROUP BY 1, 2")
def app_triple_product(spark, d):
    """Order × part, part × supplier, supplier × nation in one weighted coarsening."""
    return graphs.triple_product(cells(spark, d, "order_part"), cells(spark, d, "part_supp"), cells(spark, d, "supp_nation"))


@query(f"WITH {SUCC}, e AS (SELECT DISTINCT least(i, j) AS i, greatest(i, j) AS j FROM g WHERE i <> j AND u < 520000) SELECT count(*)::BIGINT AS triangles FROM e x JOIN e y ON x.j = y.i JOIN e z ON z.i = x.i AND z.j = y.j")
def app_triangles_maintained(spark, d):
    """The triangle count after insertions: only triangles with a new edge are counted anew."""
    g = drawn(spark, d, "user_succ")
    old = g.where("u < 500000").select("i", "j", "v")
    return graphs.triangles_after(graphs.triangles(old), old, g.where("u between 500000 and 519999").select("i", "j", "v"))


@query(f"WITH a AS ({SQL['order_part']}), p AS (SELECT x.j AS i, y.j, count(*)::BIGINT AS v FROM a x JOIN a y ON x.i = y.i WHERE x.j <> y.j GROUP BY 1, 2) SELECT i, j, v, rank FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j)::INT AS rank FROM p) WHERE rank <= 5")
def app_copurchase_topk(spark, d):
    return graphs.top_partners(graphs.cooccurrence(cells(spark, d, "order_part")), 5)


@query(f"WITH a AS (SELECT * FROM ({drawn_sql('order_part')}) WHERE u < 510000) SELECT x.j AS i, y.j, sum(x.v * y.v)::BIGINT AS v FROM a x JOIN a y ON x.i = y.i GROUP BY 1, 2")
def app_copurchase_dynamic(spark, d):
    a = drawn(spark, d, "order_part")
    old, new = a.where("u < 500000").select("i", "j", "v"), a.where("u between 500000 and 509999").select("i", "j", "v")
    c = materialize(multiply.spgemm(old, old, trans=(True, False)), "c")
    return graphs.cooccurrence_after(c, old, new)


DOC = "w AS (SELECT doc_id AS i, unnest(regexp_extract_all(lower(text), '([a-z0-9]+)', 1)) AS w FROM documents), m AS (SELECT i, w, count(*) AS v FROM w GROUP BY 1, 2), f AS (SELECT w FROM m GROUP BY 1 HAVING count(*) BETWEEN 2 AND 20)"


def doc_terms(spark, d):
    docs = inst.read(spark, d, "documents")
    w = docs.select(F.col("doc_id").alias("i"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z0-9]+)"), F.lit(1))).alias("w"))
    return w.groupBy("i", F.xxhash64("w").alias("j")).agg(F.count("*").alias("v"))


@query(f"WITH {DOC} SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS v FROM m a JOIN m b USING (w) JOIN f USING (w) WHERE a.i < b.i GROUP BY 1, 2 HAVING sum(a.v * b.v) >= 3")
def app_doc_similarity(spark, d):
    m = doc_terms(spark, d)
    rare = m.groupBy("j").agg(F.count("*").alias("n")).where("n between 2 and 20").select("j")
    return graphs.similarity(m.join(rare, "j", "left_semi").select("i", "j", "v"), 3)


@query()
def app_doc_similarity_whole(spark, d):
    """app_doc_similarity with all terms, however many documents hold them."""
    return graphs.similarity(doc_terms(spark, d), 3, tiled=True)


@query("WITH c AS (SELECT date_trunc('day', ts) AS s, user_id AS i, json_extract_string(props, '$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1, 2, 3) SELECT s::TIMESTAMP AS start, a.i, b.i AS j, sum(a.n * b.n)::BIGINT AS v FROM c a JOIN c b USING (s, k) WHERE a.i < b.i GROUP BY 1, 2, 3")
def app_two_hop_daily(spark, d):
    out = graphs.two_hop_by_window(inst.read(spark, d, "events"))
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(f"WITH {SUCC}, a AS (SELECT i, j, v FROM g WHERE u < 520000), b AS (SELECT * FROM a) {product_sql('a', 'b')}")
def app_square_maintained(spark, d):
    """A·A kept under insertions: one matrix is both operands, so both sides change at once."""
    g = drawn(spark, d, "user_succ")
    old = g.where("u < 500000").select("i", "j", "v")
    view = ProductView.create(old, old, bits=False)
    batch = updates.UpdateBatch.build(g.where("u between 500000 and 519999").select("i", "j", "v"))
    view.update(batch, batch, method="algebraic")
    return view.result()


