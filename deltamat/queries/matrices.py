"""Construction, element-wise operations, layouts, updates and redistribution."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamat.functions.semiring import PLUS_TIMES
from deltamat.operators import layout, matrix, updates
from deltamat.operators.layout import Affine, Grid
from deltamat.queries.base import SQL, cells, drawn, drawn_sql, query
from deltamat.sources import instances as inst
from deltamat.sources import store
from deltamat.sources.scratch import new_path

HALF = "u < 500000"
#: A batch on the order × part matrix: 1 % deleted, 1 % set to v + 100, 1 % new.
LATER = "u < 520000"


@query(SQL["part_supp"])
def construct_part_supp(spark, d):
    return inst.part_supp(spark, d)


@query("SELECT l_partkey AS i, l_suppkey AS j, CAST(max_by(l_quantity, {'q': l_extendedprice, 'v': l_quantity}) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2")
def construct_dups_last(spark, d):
    m = matrix.from_df(inst.read(spark, d, "lineitem"), "l_partkey", "l_suppkey", "l_quantity", PLUS_TIMES, "last", "l_extendedprice")
    return m.withColumn("v", F.col("v").cast("long"))


@query(f"WITH m AS ({SQL['user_succ']}) SELECT i, j, sum(v)::BIGINT AS v FROM (SELECT * FROM m UNION ALL SELECT j, i, v FROM m WHERE i <> j) GROUP BY 1, 2")
def symmetrize_succ(spark, d):
    return matrix.symmetrize(inst.user_succ(spark, d))


PERM = Affine(2_000_003), Affine(200_003)


@query(f"SELECT (i * 7919 + 13) % 2000003 AS i, (j * 7919 + 13) % 200003 AS j, v FROM ({SQL['part_supp']})")
def permute_affine(spark, d):
    return layout.permute(inst.part_supp(spark, d), *PERM)


@query(SQL["part_supp"])
def unpermute_affine(spark, d):
    return layout.unpermute(layout.permute(inst.part_supp(spark, d), *PERM), *PERM)


Q = 4
BLOCKS = "floor(i * 4 / n)::INT AS bi, floor(j * 4 / m)::INT AS bj"
DIMS = "(SELECT max(p_partkey) + 1 AS n FROM part), (SELECT max(s_suppkey) + 1 AS m FROM supplier)"


def part_supp_grid(spark, d, rows=None, cols=None) -> Grid:
    return Grid(*inst.dims(spark, d, ("part", "p_partkey"), ("supplier", "s_suppkey")), Q, None, rows, cols)


@query(f"SELECT {BLOCKS}, count(*)::BIGINT AS nnz FROM ({SQL['part_supp']}), {DIMS} GROUP BY 1, 2")
def grid_block_nnz(spark, d):
    laid = layout.assign_grid(inst.part_supp(spark, d), part_supp_grid(spark, d))
    return laid.groupBy("bi", "bj").agg(F.count("*").alias("nnz"))


@query(f"SELECT * FROM ({SQL['part_supp']})")
def dcsr_roundtrip(spark, d):
    return layout.from_dcsr(layout.to_dcsr(inst.part_supp(spark, d), part_supp_grid(spark, d)))


@query(f"SELECT * FROM ({SQL['part_supp']})")
def dcsc_roundtrip(spark, d):
    return layout.from_dcsc(layout.to_dcsc(inst.part_supp(spark, d), part_supp_grid(spark, d)))


@query(f"SELECT * FROM ({SQL['part_supp']})")
def csr_roundtrip(spark, d):
    return layout.from_csr(layout.to_csr(inst.part_supp(spark, d), part_supp_grid(spark, d)))


@query(
    f"WITH c AS (SELECT {BLOCKS}, i, count(*) AS n FROM ({SQL['part_supp']}), {DIMS} GROUP BY 1, 2, 3) "
    'SELECT bi, bj, i, (sum(n) OVER w - n)::BIGINT AS start, (sum(n) OVER w)::BIGINT AS "end" FROM c WINDOW w AS (PARTITION BY bi, bj ORDER BY i)'
)
def csr_rowptr(spark, d):
    return layout.csr_row_pointers(inst.part_supp(spark, d), part_supp_grid(spark, d))


@query(
    f"WITH b AS (SELECT {BLOCKS}, n, count(*) AS nnz, count(DISTINCT i) AS r, count(DISTINCT j) AS c FROM ({SQL['part_supp']}), {DIMS} GROUP BY ALL), "
    "t AS (SELECT sum(nnz) AS nnz, sum(2 * r + 1) AS dr, sum(2 * c + 1) AS dc, any_value(n) AS n FROM b) "
    "SELECT 'coo' AS kind, (3 * nnz)::BIGINT AS words FROM t UNION ALL SELECT 'csr', (2 * nnz + 16 + n * 4)::BIGINT FROM t "
    "UNION ALL SELECT 'dcsr', (2 * nnz + dr)::BIGINT FROM t UNION ALL SELECT 'dcsc', (2 * nnz + dc)::BIGINT FROM t"
)
def layout_words(spark, d):
    return layout.layout_words(inst.part_supp(spark, d), part_supp_grid(spark, d))


@query(f"SELECT (i % 6)::INT AS thread, count(*)::BIGINT AS nnz FROM ({SQL['order_part']}) GROUP BY 1")
def thread_buckets(spark, d):
    return layout.thread_buckets(inst.order_part(spark, d), 6)


@query(
    f"WITH a AS ({drawn_sql('order_part')}) SELECT b AS batch, count(*)::BIGINT AS nnz, count(*) <= 0.1 * (SELECT max(o_orderkey) + 1 FROM orders) AND count(*) <= 0.1 * (SELECT max(p_partkey) + 1 FROM part) AS hypersparse "
    "FROM (SELECT *, 1 AS b FROM a WHERE u < 1000 UNION ALL SELECT *, 2 FROM a WHERE u < 100000) GROUP BY 1"
)
def hypersparse_flags(spark, d):
    a = drawn(spark, d, "order_part")
    n, k = inst.dims(spark, d, ("orders", "o_orderkey"), ("part", "p_partkey"))
    out = [(b, (m := matrix.SparseMatrix(a.where(f"u < {u}"), n, k)).nnz(), m.is_hypersparse()) for b, u in ((1, 1000), (2, 100_000))]
    return spark.createDataFrame(out, "batch int, nnz long, hypersparse boolean")


@query(f"WITH a AS ({drawn_sql('part_supp')}), x AS (SELECT * FROM a WHERE u < 700000 UNION ALL SELECT * FROM a WHERE u >= 300000) SELECT i, j, sum(v)::BIGINT AS v FROM x GROUP BY 1, 2")
def ewise_add(spark, d):
    a = drawn(spark, d, "part_supp")
    return matrix.ewise_add(a.where("u < 700000"), a.where("u >= 300000"))


@query(f"WITH a AS ({drawn_sql('user_succ')}) SELECT i, j, v * v AS v FROM a WHERE u < 700000 AND u >= 300000")
def ewise_mult(spark, d):
    a = drawn(spark, d, "user_succ")
    return matrix.ewise_mult(a.where("u < 700000"), a.where("u >= 300000"))


@query(f"SELECT j AS i, i AS j, v FROM ({SQL['part_supp']})")
def transpose(spark, d):
    return matrix.transpose(inst.part_supp(spark, d))


@query(f"SELECT i, sum(v)::BIGINT AS v FROM ({SQL['part_supp']}) GROUP BY 1")
def reduce_rows(spark, d):
    return matrix.reduce_rows(inst.part_supp(spark, d))


@query(f"SELECT sum(v)::BIGINT AS v FROM ({SQL['part_supp']})")
def reduce_all(spark, d):
    return matrix.reduce_all(inst.part_supp(spark, d))


@query(f"SELECT i, j, v - 25 AS v FROM ({SQL['part_supp']}) WHERE v <> 25")
def prune_zeros(spark, d):
    return matrix.prune_zeros(matrix.apply(inst.part_supp(spark, d), lambda v: v - 25))


@query(f"SELECT count(*)::BIGINT AS nnz, count(*) FILTER (v <> 25)::BIGINT AS nnz_numerical, count(DISTINCT i)::BIGINT AS nz_rows, count(DISTINCT j)::BIGINT AS nz_cols FROM ({SQL['part_supp']})")
def matrix_counts(spark, d):
    return matrix.counts(matrix.apply(inst.part_supp(spark, d), lambda v: v - 25))


@query(f"SELECT i, j, v FROM ({SQL['user_succ']}) WHERE i > j")
def lower_triangle(spark, d):
    return matrix.tril(inst.user_succ(spark, d))


@query(
    f"WITH c AS (SELECT i, row_number() OVER (ORDER BY i) - 1 AS r FROM (SELECT DISTINCT o_custkey AS i FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_nationkey = 3)) "
    f"SELECT r AS i, m.j, m.v FROM ({SQL['cust_order']}) m JOIN c USING (i)"
)
def extract_nation(spark, d):
    m = inst.cust_order(spark, d)
    rows = inst.read(spark, d, "customer").where("c_nationkey = 3").select(F.col("c_custkey").alias("i")).join(m.select("i").distinct(), "i", "left_semi")
    return matrix.extract(m, rows=rows, relabel=True)


@query(f"SELECT i, j, CASE WHEN i < 50 AND j < 50 THEN 1 ELSE v END::BIGINT AS v FROM ({SQL['user_succ']}) WHERE NOT (i < 50 AND j < 50) OR (i + j) % 2 = 0")
def assign_region(spark, d):
    m = inst.user_succ(spark, d)
    sub = m.where("i < 50 and j < 50 and (i + j) % 2 = 0").withColumn("v", F.lit(1).cast("long"))
    index = spark.range(50)
    return matrix.assign(m, sub, index.select(F.col("id").alias("i")), index.select(F.col("id").alias("j")))


@query(f"SELECT deg, count(*)::BIGINT AS n FROM (SELECT i, count(*)::BIGINT AS deg FROM ({SQL['user_succ']}) GROUP BY 1) GROUP BY 1")
def degree_histogram(spark, d):
    return matrix.degree_histogram(inst.user_succ(spark, d))


@query(f"SELECT a.i, sum(a.v * x.v)::BIGINT AS v FROM ({SQL['part_supp']}) a JOIN (SELECT s_suppkey AS i, s_nationkey AS v FROM supplier) x ON a.j = x.i GROUP BY 1")
def spmv_nation(spark, d):
    x = inst.read(spark, d, "supplier").select(F.col("s_suppkey").alias("i"), F.col("s_nationkey").cast("long").alias("v"))
    return matrix.spmv(inst.part_supp(spark, d), x)


@query("SELECT r.i * 5 + y.i AS i, r.j * 5 + y.j AS j, (r.v * y.v)::BIGINT AS v FROM (SELECT n_nationkey::BIGINT AS i, n_regionkey::BIGINT AS j, 1 AS v FROM nation) r, (SELECT r_regionkey::BIGINT AS i, r_regionkey::BIGINT AS j, r_regionkey + 1 AS v FROM region) y")
def kronecker_small(spark, d):
    x = inst.assignment(spark, d, "nation", "n_nationkey", "n_regionkey")
    y = inst.read(spark, d, "region").select(F.col("r_regionkey").cast("long").alias("i"), F.col("r_regionkey").cast("long").alias("j"), (F.col("r_regionkey") + 1).cast("long").alias("v"))
    return matrix.kronecker(x, y, 5, 5)


@query(f"WITH m AS ({SQL['cust_nation']}), n AS (SELECT max(c_custkey) + 1 AS n FROM customer) SELECT i, j + n AS j, v FROM m, n UNION ALL SELECT j + n, i, v FROM m, n")
def bipartite_square(spark, d):
    n = inst.dims(spark, d, ("customer", "c_custkey"))[0]
    return matrix.bipartite(inst.assignment(spark, d, "customer", "c_custkey", "c_nationkey"), n)


@query(f"SELECT i, j, v, rank FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j)::INT AS rank FROM ({SQL['user_succ']})) WHERE rank <= 3")
def topk_per_row(spark, d):
    return matrix.topk_per_row(inst.user_succ(spark, d), 3)


A_DRAWN = f"a AS ({drawn_sql('order_part')})"


@query(f"WITH {A_DRAWN} SELECT i, j, CASE WHEN u < 10000 THEN 2 * v ELSE v END::BIGINT AS v FROM a WHERE u < 510000")
def update_add(spark, d):
    a = drawn(spark, d, "order_part")
    return updates.apply_add(a.where(HALF), a.where("u < 10000 or u between 500000 and 509999"))


@query(f"WITH {A_DRAWN} SELECT i, j, CASE WHEN u < 10000 OR u >= 500000 THEN v + 1 ELSE v END::BIGINT AS v FROM a WHERE u < 510000")
def update_merge(spark, d):
    a = drawn(spark, d, "order_part")
    return updates.apply_merge(a.where(HALF), a.where("u < 10000 or u between 500000 and 509999").withColumn("v", F.col("v") + 1))


@query(f"WITH {A_DRAWN} SELECT i, j, v FROM a WHERE u < 500000 AND u >= 10000")
def update_mask(spark, d):
    a = drawn(spark, d, "order_part")
    return updates.apply_mask(a.where(HALF), a.where("u < 10000"))


def mixed_batch(a, seq: int = 1):
    """Deletes below 10000, raises below 20000, inserts above the half; each cell once stale before."""
    deleted = a.where("u < 10000").select("i", "j", "v", F.lit("del").alias("op"), F.lit(seq).alias("seq"))
    raised = a.where("u between 10000 and 19999").select("i", "j", (F.col("v") + 100).alias("v"), F.lit("set").alias("op"), F.lit(seq).alias("seq"))
    new = a.where("u between 500000 and 509999").select("i", "j", "v", F.lit("set").alias("op"), F.lit(seq).alias("seq"))
    now = deleted.unionByName(raised).unionByName(new)
    stale = now.select("i", "j", F.lit(-1).cast("long").alias("v"), F.lit("set").alias("op"), F.lit(seq - 1).alias("seq"))
    return updates.UpdateBatch.build(now.unionByName(stale), seq)


MIXED = "SELECT i, j, CASE WHEN u < 20000 THEN v + 100 ELSE v END::BIGINT AS v FROM a WHERE u >= 10000 AND u < 510000"


@query(f"WITH {A_DRAWN} {MIXED}")
def update_mixed_seq(spark, d):
    a = drawn(spark, d, "order_part")
    return updates.apply_ops(a.where(HALF), mixed_batch(a))


@query(f"WITH {A_DRAWN} SELECT i, j, CASE WHEN u < 10000 THEN -v WHEN u < 20000 THEN 100 ELSE v END::BIGINT AS v FROM a WHERE u < 20000 OR u BETWEEN 500000 AND 509999")
def update_delta_ring(spark, d):
    a = drawn(spark, d, "order_part")
    old = a.where(HALF).select("i", "j", "v")
    return updates.delta_of(updates.apply_ops(old, mixed_batch(a)), old)


@query(f"WITH {A_DRAWN} SELECT i, j FROM a WHERE u < 20000 OR u BETWEEN 500000 AND 509999")
def update_pattern(spark, d):
    a = drawn(spark, d, "order_part")
    old = a.where(HALF).select("i", "j", "v")
    return updates.changed_pattern(updates.apply_ops(old, mixed_batch(a)), old)


@query(f"WITH {A_DRAWN} SELECT CASE WHEN u < 10000 THEN 'delete' WHEN u < 20000 THEN 'replace' ELSE 'insert' END AS reason, count(*)::BIGINT AS n FROM a WHERE u < 20000 OR u BETWEEN 500000 AND 509999 GROUP BY 1")
def update_classify(spark, d):
    from deltamat.functions.semiring import MIN_PLUS

    a = drawn(spark, d, "order_part")
    return updates.reasons(a.where(HALF).select("i", "j", "v"), mixed_batch(a), MIN_PLUS)


SRC = "('0x' || substr(md5(concat_ws('|', i, j, 'src')), 1, 8))::BIGINT"
TRACE = (
    f"WITH a AS ({drawn_sql('order_part')}), t AS (SELECT floor(i * 4 / n)::INT AS bi, floor(j * 4 / m)::INT AS bj, ({SRC} % 16)::INT AS src "
    "FROM a, (SELECT max(o_orderkey) + 1 AS n FROM orders), (SELECT max(p_partkey) + 1 AS m FROM part) WHERE u < 50000), r AS (SELECT src, bi * 4 + src % 4 AS mid, bi * 4 + bj AS dst FROM t)"
)


def step_sql(name: str, a: str, b: str) -> str:
    return f"SELECT '{name}' AS step, coalesce(sum(n), 0)::BIGINT AS moved, coalesce(max(p), 0)::BIGINT AS peers FROM (SELECT {a}, count(*) AS n, count(DISTINCT {b}) AS p FROM r WHERE {a} <> {b} GROUP BY 1)"


@query(f"{TRACE} {step_sql('first', 'src', 'mid')} UNION ALL {step_sql('second', 'mid', 'dst')} UNION ALL {step_sql('direct', 'src', 'dst')}")
def redistribute_two_step_counts(spark, d):
    from deltamat.plans import cost

    a = drawn(spark, d, "order_part").where("u < 50000")
    g = Grid(*inst.dims(spark, d, ("orders", "o_orderkey"), ("part", "p_partkey")), Q)
    return cost.redistribution(updates.redistribute(a, g, "two_step"))


BLOCK_COUNTS = f"WITH a AS ({drawn_sql('order_part')}) SELECT floor(i * 4 / n)::INT AS bi, floor(j * 4 / m)::INT AS bj, count(*)::BIGINT AS nnz FROM a, (SELECT max(o_orderkey) + 1 AS n FROM orders), (SELECT max(p_partkey) + 1 AS m FROM part) WHERE u < 50000 GROUP BY 1, 2"


def _dealt(method):
    def run(spark, d):
        a = drawn(spark, d, "order_part").where("u < 50000")
        g = Grid(*inst.dims(spark, d, ("orders", "o_orderkey"), ("part", "p_partkey")), Q)
        return updates.redistribute(a, g, method).groupBy("bi", "bj").agg(F.count("*").alias("nnz"))

    return run


query(BLOCK_COUNTS, "redistribute_one_step_counts")(_dealt("one_step"))
query(BLOCK_COUNTS, "redistribute_sorted_counts")(_dealt("sort"))


def _store(kind):
    def run(spark, d):
        a = drawn(spark, d, "order_part")
        g = Grid(*inst.dims(spark, d, ("orders", "o_orderkey"), ("part", "p_partkey")), Q)
        s = kind.create(a.where(HALF).select("i", "j", "v"), new_path(spark, "store"), g)
        s.apply(mixed_batch(a))
        s.apply(mixed_batch(a))  # a replay changes nothing
        old = s.at(0).withColumn("version", F.lit(0))
        return old.unionByName(s.current().withColumn("version", F.lit(s.version())))

    return run


VERSIONS = f"WITH {A_DRAWN} SELECT i, j, v, 0 AS version FROM a WHERE u < 500000 UNION ALL SELECT *, 1 FROM ({MIXED})"
query(VERSIONS, "store_versions")(_store(store.MatrixStore))
query(VERSIONS, "store_delta_versions")(_store(store.DeltaStore))
query(VERSIONS, "store_rebuild_baseline")(_store(store.StaticStore))


@query(f"WITH {A_DRAWN} SELECT i, j, v FROM a WHERE u < 500000 AND i = (SELECT min(i) FROM a)")
def store_row_lookup(spark, d):
    a = drawn(spark, d, "order_part")
    g = Grid(*inst.dims(spark, d, ("orders", "o_orderkey"), ("part", "p_partkey")), Q)
    s = store.MatrixStore.create(a.where(HALF).select("i", "j", "v"), new_path(spark, "store"), g)
    return s.row(a.agg(F.min("i")).first()[0])


@query(f"SELECT batch, count(*)::BIGINT AS n, sum(v)::BIGINT AS total FROM (SELECT v, (u - 500000) // 10000 AS batch FROM ({drawn_sql('order_part')}) WHERE u >= 500000 AND u < 600000) GROUP BY 1")
def draw_batches(spark, d):
    a = drawn(spark, d, "order_part").where("u >= 500000 and u < 600000")
    return a.withColumn("batch", F.floor((F.col("u") - 500000) / 10000).cast("long")).groupBy("batch").agg(F.count("*").alias("n"), F.sum("v").alias("total"))


@query("SELECT e.event_id AS e, (" + " + ".join(f"(CASE WHEN x{k} >= 195 THEN {1 << (11 - k)} ELSE 0 END)" for k in range(12)) + ")::BIGINT AS i, (" + " + ".join(f"(CASE WHEN (x{k} >= 146 AND x{k} < 195) OR x{k} >= 243 THEN {1 << (11 - k)} ELSE 0 END)" for k in range(12)) + ")::BIGINT AS j FROM (SELECT event_id, " + ", ".join(f"('0x' || substr(h, {2 * k + 1}, 2))::INT AS x{k}" for k in range(12)) + " FROM (SELECT event_id, md5(concat_ws('|', event_id, 1)) AS h FROM events WHERE event_id IS NOT NULL)) e")
def rmat_edges(spark, d):
    """An edge of a power-law graph for every event, from the digest of its id."""
    return inst.rmat_of(inst.read(spark, d, "events").where("event_id is not null").select(F.col("event_id").alias("e")), 12)


def rmat_cells(spark, d):
    return rmat_edges(spark, d).groupBy("i", "j").agg(F.count("*").alias("v"))


RMAT_CELLS = "SELECT i, j, count(*) AS v FROM rm GROUP BY 1, 2"


def _balance_sql(perm: bool) -> str:
    from deltamat.queries.base import ORACLES

    at = "((i * 7919 + 13) % 4096) * 4 // 4096 AS bi, ((j * 7919 + 13) % 4096) * 4 // 4096 AS bj" if perm else "i * 4 // 4096 AS bi, j * 4 // 4096 AS bj"
    return f"WITH rm AS ({ORACLES['rmat_edges']}), b AS (SELECT {at}, count(*) AS n FROM ({RMAT_CELLS}) GROUP BY 1, 2) SELECT max(n)::BIGINT AS most, (sum(n) / 16)::DOUBLE AS mean, round(max(n) / (sum(n) / 16), 6)::DOUBLE AS ratio FROM b"


def _balance(perm):
    def run(spark, d):
        from deltamat.plans import cost

        p = Affine(4096) if perm else None
        return cost.balance(rmat_cells(spark, d), 4096, 4096, 4, p, p)

    return run


query(_balance_sql(True), "grid_balance_perm")(_balance(True))
query(_balance_sql(False), "grid_balance_plain")(_balance(False))



# ---- shapes, vectors and dictionaries --------------------------------------------------------

PS, OP = f"p AS ({SQL['part_supp']})", f"o AS ({SQL['order_part']})"
SIZES = "dims AS (SELECT (SELECT max(p_partkey) + 1 FROM part) AS k, (SELECT max(s_suppkey) + 1 FROM supplier) AS m)"


@query(f"WITH {PS}, {SIZES} SELECT i, j, v FROM p UNION ALL SELECT i, j + m, 2 * v FROM p, dims")
def matrix_hstack(spark, d):
    x = cells(spark, d, "part_supp")
    m = inst.dims(spark, d, ("supplier", "s_suppkey"))[0]
    return matrix.hstack(x, matrix.scale(x, 2), m)


@query(f"WITH {PS}, {SIZES} SELECT i, j, v FROM p UNION ALL SELECT i + k, j, 2 * v FROM p, dims")
def matrix_vstack(spark, d):
    x = cells(spark, d, "part_supp")
    k = inst.dims(spark, d, ("part", "p_partkey"))[0]
    return matrix.vstack(x, matrix.scale(x, 2), k)


@query(f"WITH {PS}, {SIZES} SELECT p.i, p.j, p.v FROM p, dims WHERE p.i < k // 2 AND p.j < m // 2")
def matrix_resize(spark, d):
    k, m = inst.dims(spark, d, ("part", "p_partkey"), ("supplier", "s_suppkey"))
    return matrix.SparseMatrix(cells(spark, d, "part_supp"), k, m).resized(k // 2, m // 2).cells


@query(f"WITH {OP} SELECT j AS i, sum(v * (i % 5))::BIGINT AS v FROM o GROUP BY 1")
def matrix_vxm(spark, d):
    a = cells(spark, d, "order_part")
    return matrix.vxm(a.select("i", (F.col("i") % 5).alias("v")).distinct(), a)


@query("SELECT event_type AS key, count(*)::BIGINT AS n FROM events WHERE event_type IS NOT NULL GROUP BY 1")
def matrix_dictionary(spark, d):
    """Rows by the ids of a text column, looked up again in its dictionary."""
    coded, names = matrix.dictionary_encode(inst.read(spark, d, "events"), "event_type")
    counts = coded.groupBy(F.col("event_type_id").alias("id")).agg(F.count("*").alias("n"))
    return counts.join(names, "id").select("key", "n")


@query("SELECT max(label)::BIGINT AS most, count(*)::BIGINT AS n, count(DISTINCT label)::BIGINT AS labels FROM (SELECT DISTINCT vec_id, label FROM embeddings)")
def matrix_ones_and_diagonal(spark, d):
    """The label vector as a diagonal, and its pattern."""
    x = matrix.diag_of(inst.vec_label(spark, d).select("i", F.col("j").alias("v")))
    ones = matrix.ones_pattern(x).groupBy().agg(F.sum("v").alias("n"))
    return x.agg(F.max("v").alias("most"), F.count_distinct("v").alias("labels")).crossJoin(ones).select("most", "n", "labels")  # single rows


TERMS = "SELECT i, w, count(*)::BIGINT AS v FROM (SELECT doc_id AS i, unnest(regexp_extract_all(lower(text), '([a-z0-9]+)', 1)) AS w FROM documents) GROUP BY 1, 2"


@query(f"WITH m AS ({TERMS}), f AS (SELECT w FROM m GROUP BY 1 HAVING count(*) >= 2) SELECT i, count(*)::BIGINT AS terms, sum(v)::BIGINT AS words FROM m JOIN f USING (w) GROUP BY 1")
def instance_doc_term(spark, d):
    return inst.doc_term(spark, d).groupBy("i").agg(F.count("*").alias("terms"), F.sum("v").alias("words"))


@query("SELECT i, count(DISTINCT t)::BIGINT AS targets, count(*)::BIGINT AS links FROM (SELECT page_id AS i, unnest(regexp_extract_all(html, 'href=\"([^\"]+)', 1)) AS t FROM pages) GROUP BY 1")
def instance_page_link(spark, d):
    return inst.page_link(spark, d).groupBy("i").agg(F.count("*").alias("targets"), F.sum("v").alias("links"))


@query("SELECT conv_id AS i, count(DISTINCT coalesce(role, ''))::BIGINT AS roles, count(*)::BIGINT AS turns FROM conversations GROUP BY 1")
def instance_turn_role(spark, d):
    return inst.turn_role(spark, d).groupBy("i").agg(F.count("*").alias("roles"), F.sum("v").alias("turns"))
