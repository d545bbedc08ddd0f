"""The relational and streaming operators around the methods, one query each."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from deltamat.functions import udfs
from deltamat.functions.semiring import PLUS_TIMES
from deltamat.operators import layout, matrix, multiply, updates
from deltamat.plans.stored import StoredProduct
from deltamat.plans.view import ProductView
from deltamat.queries.base import SQL, cells, drawn, drawn_sql, product_sql, query
from deltamat.sources import instances as inst
from deltamat.sources import readers
from deltamat.sources.scratch import new_path
from deltamat.streaming import maintain as st

PS = SQL["part_supp"]


@query("SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01'")
def op_scan_prune(spark, d):
    return inst.read(spark, d, "lineitem").where("l_shipdate >= timestamp_ntz'1995-01-01' and l_shipdate < timestamp_ntz'1996-01-01'").select("l_orderkey", "l_partkey", "l_quantity")


@query(f"SELECT i, j, v::DOUBLE AS v FROM ({SQL['trade']})")
def op_scan_csv_json_roundtrip(spark, d):
    path = new_path(spark, "text")
    m = cells(spark, d, "trade").withColumn("v", F.col("v").cast("double"))
    m.write.option("header", True).csv(f"{path}/csv")
    readers.csv_cells(spark, f"{path}/csv").write.json(f"{path}/json")
    return readers.json_cells(spark, f"{path}/json")


@query(f"SELECT i, j, v::DOUBLE AS v, false AS malformed FROM ({SQL['user_succ']}) UNION ALL SELECT NULL, NULL, 1.0, true")
def op_edge_text_reader(spark, d):
    path = new_path(spark, "edges")
    readers.write_edge_text(cells(spark, d, "user_succ"), path)
    spark.range(1).select(F.lit("# a comment\n\nno numbers").alias("value")).write.mode("append").text(path)
    return readers.edge_text(spark, path)


@query(f"SELECT i, j, v::DOUBLE AS v FROM ({SQL['trade']})")
def op_matrix_market_reader(spark, d):
    path = new_path(spark, "mtx")
    m = cells(spark, d, "trade")
    head = spark.createDataFrame([(0, "%%MatrixMarket matrix coordinate integer general"), (1, "25 25 " + str(m.count()))], "o long, value string")
    body = m.select(F.lit(2).cast("long").alias("o"), F.concat_ws(" ", F.col("i") + 1, F.col("j") + 1, "v").alias("value"))
    head.unionByName(body).coalesce(1).sortWithinPartitions("o").select("value").write.text(path)
    return readers.matrix_market(spark, path)


@query(f"SELECT i, j, v FROM ({PS}) WHERE v > 30 AND i <> j")
def op_filter_cells(spark, d):
    return matrix.offdiag(matrix.select(inst.part_supp(spark, d), "v > 30"))


@query(f"SELECT i % 100 AS i, j % 10 AS j, sum(v)::BIGINT AS v FROM ({PS}) GROUP BY 1, 2")
def op_project_remap(spark, d):
    m = inst.part_supp(spark, d)
    return matrix.from_df(m, F.col("i") % 100, F.col("j") % 10, "v")


A = f"a AS ({drawn_sql('order_part')})"


@query(f"WITH {A} SELECT i, j, v FROM a WHERE u < 100000")
def op_join_semi(spark, d):
    a = drawn(spark, d, "order_part")
    return a.select("i", "j", "v").join(a.where("u < 100000").select("i", "j"), ["i", "j"], "left_semi")


@query(f"WITH {A} SELECT i, j, v FROM a WHERE u >= 100000")
def op_join_anti(spark, d):
    a = drawn(spark, d, "order_part")
    return updates.apply_mask(a, a.where("u < 100000"))


@query(f"WITH {A} SELECT i, j, v, CASE WHEN u >= 300000 THEN v END AS w FROM a WHERE u < 600000")
def op_join_left(spark, d):
    a = drawn(spark, d, "order_part")
    return a.where("u < 600000").select("i", "j", "v").join(a.where("u >= 300000").select("i", "j", F.col("v").alias("w")), ["i", "j"], "left")


@query(f"WITH {A} SELECT i, j, CASE WHEN u < 600000 THEN v END AS v, CASE WHEN u >= 300000 THEN v END AS w FROM a")
def op_join_full(spark, d):
    a = drawn(spark, d, "order_part")
    return a.where("u < 600000").select("i", "j", "v").join(a.where("u >= 300000").select("i", "j", F.col("v").alias("w")), ["i", "j"], "full")


@query(f"WITH b AS (SELECT range AS block, range * 16 AS lo, (range + 1) * 16 AS hi FROM range(100)) SELECT block, count(*)::BIGINT AS n FROM ({SQL['user_succ']}) JOIN b ON i >= lo AND i < hi GROUP BY 1")
def op_join_theta(spark, d):
    """A range join on a table of block bounds of fixed size."""
    b = spark.range(100).select(F.col("id").alias("block"), (F.col("id") * 16).alias("lo"), ((F.col("id") + 1) * 16).alias("hi"))
    m = inst.user_succ(spark, d)
    return m.join(F.broadcast(b), (m.i >= b.lo) & (m.i < b.hi)).groupBy("block").agg(F.count("*").alias("n"))


@query("WITH w AS (SELECT range AS batch, TIMESTAMP '2024-01-01' + INTERVAL 3 DAY * range AS lo FROM range(20)) SELECT batch, count(*)::BIGINT AS n FROM events JOIN w ON ts >= lo AND ts < lo + INTERVAL 3 DAY GROUP BY 1")
def op_join_interval(spark, d):
    w = spark.range(20).select(F.col("id").alias("batch"), F.expr("timestamp_ntz'2024-01-01' + make_dt_interval(cast(3 * id as int))").alias("lo"))
    e = inst.read(spark, d, "events")
    return e.join(F.broadcast(w), (e.ts >= w.lo) & (e.ts < F.expr("lo + interval 3 days"))).groupBy("batch").agg(F.count("*").alias("n"))


@query(
    "WITH c AS (SELECT user_id, ts, count(*) AS n FROM events GROUP BY 1, 2), ver AS (SELECT user_id, ts, (sum(n) OVER (PARTITION BY user_id ORDER BY ts))::BIGINT AS v FROM c), p AS (SELECT user_id, ts + INTERVAL 1 HOUR AS at, event_id FROM events) "
    "SELECT p.event_id, (SELECT max(v) FROM ver WHERE ver.user_id = p.user_id AND ver.ts <= p.at)::BIGINT AS v FROM p"
)
def asof_cell(spark, d):
    """The last version of a user's running count at a probe's time: one sorted pass over both."""
    e = inst.read(spark, d, "events")
    running = Window.partitionBy("user_id").orderBy("ts")
    versions = e.groupBy("user_id", "ts").agg(F.count("*").alias("n")).select("user_id", F.col("ts").alias("at"), F.sum("n").over(running).alias("v"), F.lit(None).cast("long").alias("event_id"), F.lit(0).alias("probe"))
    probes = e.select("user_id", F.expr("ts + interval 1 hour").alias("at"), F.lit(None).cast("long").alias("v"), "event_id", F.lit(1).alias("probe"))
    before = Window.partitionBy("user_id").orderBy("at", "probe").rowsBetween(Window.unboundedPreceding, 0)
    return versions.unionByName(probes).withColumn("v", F.last("v", True).over(before)).where("probe = 1").select("event_id", "v")


@query("SELECT x.n_nationkey::BIGINT AS i, y.n_nationkey::BIGINT AS j FROM nation x, nation y WHERE x.n_regionkey = y.n_regionkey AND x.n_nationkey < y.n_nationkey")
def op_pairs_small(spark, d):
    n = inst.read(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("k"), "n_regionkey")
    x, y = n.withColumnRenamed("k", "i"), n.withColumnRenamed("k", "j")
    return x.join(y, "n_regionkey").where("i < j").select("i", "j")


@query("SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, sum(l_quantity)::BIGINT AS q, max(l_quantity)::BIGINT AS most FROM lineitem GROUP BY 1, 2")
def op_agg_hash(spark, d):
    return inst.read(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("q"), F.max("l_quantity").cast("long").alias("most"))


@query("SELECT l_suppkey, count(DISTINCT l_partkey)::BIGINT AS parts FROM lineitem GROUP BY 1")
def op_agg_distinct(spark, d):
    return inst.read(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"))


@query("SELECT l_suppkey, true AS parts_close, true AS median_close FROM lineitem GROUP BY 1")
def op_agg_approx(spark, d):
    """Approximate distinct counts and medians, each within 5 % of the exact one."""
    near = lambda x, y: F.abs(x - y) <= F.greatest(F.lit(1.0), 0.05 * y)
    g = inst.read(spark, d, "lineitem").groupBy("l_suppkey")
    parts = near(F.approx_count_distinct("l_partkey", 0.02), F.count_distinct("l_partkey"))
    return g.agg(parts.alias("parts_close"), near(F.percentile_approx("l_quantity", 0.5).cast("double"), F.percentile("l_quantity", 0.5)).alias("median_close"))


@query(f"SELECT i, bit_or(v) AS o, bit_and(v) AS a, bit_xor(v) AS x, bit_count(bit_or(v))::INT AS n FROM ({SQL['order_part']}) GROUP BY 1")
def op_agg_bits(spark, d):
    return inst.order_part(spark, d).groupBy("i").agg(F.bit_or("v").alias("o"), F.bit_and("v").alias("a"), F.bit_xor("v").alias("x"), F.bit_count(F.bit_or("v")).alias("n"))


NATIONS = f"(SELECT t.v, n.n_regionkey AS r, n.n_nationkey AS k FROM ({SQL['trade']}) t JOIN nation n ON t.i = n.n_nationkey)"


def _nations(spark, d):
    n = inst.read(spark, d, "nation")
    return inst.trade(spark, d).join(n, F.col("i") == F.col("n_nationkey")).select("v", F.col("n_regionkey").alias("r"), F.col("n_nationkey").alias("k"))


def _grouped(df):
    return df.agg(F.sum("v").alias("v"), F.grouping_id().cast("int").alias("g")).select("r", "k", "v", "g")


GROUPED = "SELECT r, k, sum(v)::BIGINT AS v, grouping(r, k)::INT AS g FROM " + NATIONS + " GROUP BY "
query(GROUPED + "ROLLUP (r, k)", "op_rollup")(lambda s, d: _grouped(_nations(s, d).rollup("r", "k")))
query(GROUPED + "CUBE (r, k)", "op_cube")(lambda s, d: _grouped(_nations(s, d).cube("r", "k")))
query(GROUPED + "GROUPING SETS ((r), (k))", "op_grouping_sets")(lambda s, d: _grouped(_nations(s, d).groupingSets([[F.col("r")], [F.col("k")]], "r", "k")))


@query("SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS click, count(*) FILTER (event_type = 'purchase')::BIGINT AS purchase FROM events WHERE event_type IN ('click', 'purchase') GROUP BY 1")
def op_pivot(spark, d):
    e = inst.read(spark, d, "events").where("event_type in ('click', 'purchase')")
    return e.groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1))).select("user_id", F.coalesce("click", F.lit(0).cast("long")).alias("click"), F.coalesce("purchase", F.lit(0).cast("long")).alias("purchase"))


@query(f"SELECT i, j, v, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS rn, ntile(3) OVER (PARTITION BY i ORDER BY v DESC, j) AS t FROM ({SQL['user_succ']}) WINDOW w AS (PARTITION BY i ORDER BY v DESC)")
def op_window_rank(spark, d):
    w, total = Window.partitionBy("i").orderBy(F.desc("v")), Window.partitionBy("i").orderBy(F.desc("v"), "j")
    m = inst.user_succ(spark, d)
    return m.select("i", "j", "v", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("dr"), F.row_number().over(total).cast("long").alias("rn"), F.ntile(3).over(total).cast("long").alias("t"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS later FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def op_window_lag(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return inst.read(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("later"))


@query(f"SELECT i, j, (sum(v) OVER (PARTITION BY i ORDER BY j))::BIGINT AS running FROM ({PS})")
def op_window_running(spark, d):
    return inst.part_supp(spark, d).select("i", "j", F.sum("v").over(Window.partitionBy("i").orderBy("j")).alias("running"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def op_window_range_frame(spark, d):
    e = inst.read(spark, d, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")) / F.lit(1e6))
    return e.select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("n"))


CO = f"(WITH a AS ({SQL['order_part']}) SELECT x.j AS i, y.j, sum(x.v * y.v)::BIGINT AS v FROM a x JOIN a y ON x.i = y.i WHERE x.j < y.j GROUP BY 1, 2)"


def _co(spark, d):
    m = cells(spark, d, "order_part")
    return matrix.triu(multiply.spgemm(m, m, PLUS_TIMES, (True, False)))


query(f"SELECT * FROM {CO} ORDER BY v DESC, i, j LIMIT 100", "op_topk_global")(lambda s, d: _co(s, d).orderBy(F.desc("v"), "i", "j").limit(100))
query(f"SELECT * FROM {CO} ORDER BY v DESC, i, j LIMIT 50 OFFSET 20", "op_limit_offset")(lambda s, d: _co(s, d).orderBy(F.desc("v"), "i", "j").offset(20).limit(50))
query(f"SELECT i, j, v, rank FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j)::INT AS rank FROM {CO}) WHERE rank <= 2", "op_topk_group")(lambda s, d: matrix.topk_per_row(_co(s, d), 2))


def _sets(f):
    def run(spark, d):
        a = drawn(spark, d, "user_succ")
        return f(a.where("u < 600000").select("i", "j"), a.where("u >= 300000").select("i", "j"))

    return run


G = f"WITH g AS ({drawn_sql('user_succ')}), x AS (SELECT i, j FROM g WHERE u < 600000), y AS (SELECT i, j FROM g WHERE u >= 300000) SELECT * FROM x "
query(G + "UNION SELECT * FROM y", "op_union")(_sets(lambda x, y: x.union(y).distinct()))
query(G + "UNION ALL SELECT * FROM y", "op_union_all")(_sets(lambda x, y: x.union(y)))
query(G + "INTERSECT SELECT * FROM y", "op_intersect")(_sets(lambda x, y: x.intersect(y)))
query(G + "EXCEPT SELECT * FROM y", "op_except")(_sets(lambda x, y: x.subtract(y)))
query(f"WITH g AS ({SQL['user_succ']}), x AS (SELECT i FROM g), y AS (SELECT i FROM g WHERE v > 1) SELECT * FROM x EXCEPT ALL SELECT * FROM y", "op_except_all")(lambda s, d: (m := inst.user_succ(s, d)).select("i").exceptAll(m.where("v > 1").select("i")))


@query("SELECT h AS target, count(*)::BIGINT AS n FROM (SELECT unnest(regexp_extract_all(html, 'href=\"([^\"]+)', 1)) AS h FROM pages) GROUP BY 1")
def op_str_json_regex(spark, d):
    targets = inst.read(spark, d, "pages").select(F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)'), F.lit(1))).alias("target"))
    return targets.groupBy("target").agg(F.count("*").alias("n"))


@query("SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, count(*)::BIGINT AS n, min(date_diff('day', TIMESTAMP '1992-01-01', o_orderdate))::BIGINT AS first_day FROM orders GROUP BY 1")
def op_date_math(spark, d):
    o = inst.read(spark, d, "orders")
    return o.groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month")).agg(F.count("*").alias("n"), F.min(F.datediff("o_orderdate", F.lit("1992-01-01"))).cast("long").alias("first_day"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0))::INT AS positive FROM embeddings")
def op_array_map(spark, d):
    e = inst.read(spark, d, "embeddings")
    square = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return e.select("vec_id", F.round(square, 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))


@query(f"WITH a AS ({SQL['user_prop']}), n AS (SELECT i, sqrt(sum(v * v)) AS n FROM a GROUP BY 1) SELECT x.i, y.i AS j, round(sum(x.v * y.v) / (any_value(nx.n) * any_value(ny.n)), 6) AS v FROM a x JOIN a y ON x.j = y.j JOIN n nx ON nx.i = x.i JOIN n ny ON ny.i = y.i WHERE x.i < y.i GROUP BY 1, 2")
def op_math(spark, d):
    from deltamat.operators.graphs import cosine

    return cosine(cells(spark, d, "user_prop"))


@query(f"SELECT k, (1::BIGINT << (k % 62)::INT)::BIGINT AS bit FROM (SELECT DISTINCT j AS k FROM ({PS}))")
def op_udf_scalar(spark, d):
    udfs.register_udfs(spark)
    inst.part_supp(spark, d).select(F.col("j").alias("k")).distinct().createOrReplaceTempView("inner_indices")
    return spark.sql("SELECT k, bits_of(k, 62L) AS bit FROM inner_indices")


@query(f"WITH a AS ({SQL['user_succ']}), b AS (SELECT * FROM a) " + product_sql("a", "b"))
def op_udf_arrow(spark, d):
    udfs.register_udfs(spark)
    left, right = multiply.sides(*(cells(spark, d, "user_succ"),) * 2)
    terms = left.join(right, "k").select("i", "j", udfs.times_arrow("av", "bv").alias("t"))
    return terms.groupBy("i", "j").agg(F.sum("t").alias("v"))


@query(f"SELECT i, round(ln(sum(exp(v / 10.0))), 6)::DOUBLE AS v FROM ({SQL['user_succ']}) GROUP BY 1")
def op_udaf(spark, d):
    udfs.register_udfs(spark)
    m = inst.user_succ(spark, d)
    return m.groupBy("i").agg(F.round(udfs.log_sum_exp(F.col("v") / 10.0), 6).alias("v"))


@query(PS)
def op_udtf(spark, d):
    from deltamat.queries.matrices import part_supp_grid

    udfs.register_udfs(spark)
    layout.to_dcsr(inst.part_supp(spark, d), part_supp_grid(spark, d)).createOrReplaceTempView("packed_rows")
    return spark.sql("SELECT t.* FROM packed_rows p, LATERAL dcsr_rows(p.i, p.cols, p.vals) t")


# ---- streams ---------------------------------------------------------------------------------


def _start(df):
    return df.withColumn("start", F.col("start").cast("timestamp_ntz"))


#: Windows that the watermark has not passed at the end are not given out in append mode.
SEEN = "(SELECT max(ts) - INTERVAL 1 DAY AS wm FROM events)"
TUMBLING = "SELECT time_bucket(INTERVAL 1 DAY, ts)::TIMESTAMP AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2"
query(TUMBLING, "op_stream_tumbling")(lambda s, d: _start(st.run_to_end(st.tumbling(st.events(s, d), "1 day"), "tumbling", "complete")))
query(TUMBLING, "stream_window_batches")(lambda s, d: _start(st.tumbling(inst.read(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")), "1 day")))
query(
    "SELECT (s - INTERVAL 1 DAY * k)::TIMESTAMP AS start, event_type, count(*)::BIGINT AS n FROM (SELECT time_bucket(INTERVAL 1 DAY, ts) AS s, event_type FROM events), (SELECT range AS k FROM range(3)) GROUP BY 1, 2",
    "op_stream_sliding",
)(lambda s, d: _start(st.run_to_end(st.sliding(st.events(s, d), "3 days", "1 day"), "sliding", "complete")))


@query(
    "WITH e AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM e) "
    'SELECT min(ts)::TIMESTAMP AS start, (max(ts) + INTERVAL 6 HOUR)::TIMESTAMP AS "end", user_id, count(*)::BIGINT AS n FROM s GROUP BY user_id, no'
)
def op_stream_session(spark, d):
    out = st.run_to_end(st.sessions(st.events(spark, d), "6 hours"), "sessions", "complete")
    return out.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


@query("SELECT event_id, user_id FROM events")
def op_stream_dedup(spark, d):
    """Every event comes twice in the stream and leaves it once."""
    twice = st.events(spark, d).select("event_id", "user_id", "ts", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy"))
    return st.run_to_end(st.deduplicated(twice).select("event_id", "user_id"), "dedup")


@query(f"SELECT time_bucket(INTERVAL 1 DAY, ts)::TIMESTAMP AS start, event_type, count(*)::BIGINT AS n FROM events, {SEEN} WHERE time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= wm GROUP BY 1, 2")
def op_stream_watermark_late(spark, d):
    """Append mode: a window leaves when the watermark has passed it."""
    return _start(st.run_to_end(st.tumbling(st.events(spark, d), "1 day"), "late"))


@query(SQL["user_prop"])
def op_stream_state(spark, d):
    """The rows' hash maps kept by the stream end as the batch's matrix."""
    return st.run_to_end(st.row_state(st.events(spark, d)), "rows", "update").groupBy("i", "j").agg(F.max("v").alias("v"))


@query(f"WITH a AS ({SQL['user_prop']}), b AS (SELECT j AS i, i AS j, v FROM a) " + product_sql("a", "b"))
def stream_events_maintain(spark, d):
    """user × property times its transpose, with the left operand growing from the stream."""
    m = cells(spark, d, "user_prop")
    view = ProductView.create(matrix.empty(spark), matrix.transpose(m).select("i", "j", "v"), bits=False)
    e = st.events(spark, d)
    adds = e.select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("j"), F.lit(1).cast("long").alias("v"), F.lit("add").alias("op"), F.col("event_id").alias("seq"))
    st.stream_maintain(view, adds, method="algebraic")
    return view.result()


@query(f"WITH a AS ({SQL['user_prop']}), b AS (SELECT j AS i, i AS j, v FROM a) " + product_sql("a", "b"))
def stream_events_stored(spark, d):
    """stream_events_maintain on block stores; the stream is started a second time and changes nothing."""
    m = cells(spark, d, "user_prop")
    n, k = inst.dims(spark, d, ("events", "user_id"))[0], m.agg(F.max("j")).first()[0] + 1
    product = StoredProduct.create(matrix.empty(spark), matrix.transpose(m).select("i", "j", "v"), (n, k, n), new_path(spark, "product"), q=2)
    e, place = st.events(spark, d), new_path(spark, "maintain")
    adds = e.select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("j"), F.lit(1).cast("long").alias("v"), F.lit("add").alias("op"), F.col("event_id").alias("seq"))
    for _ in range(2):
        st.stream_maintain(product, adds, checkpoint=place)
    return product.result()
