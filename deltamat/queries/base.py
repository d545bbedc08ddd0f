"""The registry, and the SQL twins of instances and draws.

SQL here never uses a delta formula: it rebuilds the changed operands and multiplies them.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamat.sources import instances as inst
from deltamat.sources.scratch import materialize

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        if key in QUERIES:
            raise ValueError(f"two queries are called {key}")
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


def quantity_sql(i: str, j: str) -> str:
    return f"SELECT {i} AS i, {j} AS j, CAST(SUM(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2"


SQL = {
    "part_supp": quantity_sql("l_partkey", "l_suppkey"),
    "order_part": quantity_sql("l_orderkey", "l_partkey"),
    "part_order": quantity_sql("l_partkey", "l_orderkey"),
    "supp_order": quantity_sql("l_suppkey", "l_orderkey"),
    "order_cust": "SELECT DISTINCT o_orderkey AS i, o_custkey AS j, 1::BIGINT AS v FROM orders",
    "cust_order": "SELECT DISTINCT o_custkey AS i, o_orderkey AS j, 1::BIGINT AS v FROM orders",
    "user_succ": "SELECT user_id AS i, nxt AS j, count(*)::BIGINT AS v FROM (SELECT user_id, lead(user_id) OVER (ORDER BY event_id) AS nxt FROM events) WHERE nxt IS NOT NULL GROUP BY 1, 2",
    "user_prop": "SELECT user_id AS i, json_extract_string(props, '$.k')::BIGINT AS j, count(*)::BIGINT AS v FROM events GROUP BY 1, 2",
    "vec_label": "SELECT DISTINCT vec_id::BIGINT AS i, label::BIGINT AS j, 1::BIGINT AS v FROM embeddings",
    "cust_nation": "SELECT DISTINCT c_custkey::BIGINT AS i, c_nationkey::BIGINT AS j, 1::BIGINT AS v FROM customer",
    "supp_nation": "SELECT DISTINCT s_suppkey::BIGINT AS i, s_nationkey::BIGINT AS j, 1::BIGINT AS v FROM supplier",
    "trade": "SELECT c_nationkey::BIGINT AS i, s_nationkey::BIGINT AS j, CAST(SUM(l_quantity) AS BIGINT) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2",
}

MAKE = {
    "part_supp": inst.part_supp,
    "order_part": inst.order_part,
    "part_order": inst.part_order,
    "supp_order": inst.supp_order,
    "order_cust": inst.order_cust,
    "cust_order": inst.cust_order,
    "user_succ": inst.user_succ,
    "user_prop": inst.user_prop,
    "vec_label": inst.vec_label,
    "cust_nation": lambda s, d: inst.assignment(s, d, "customer", "c_custkey", "c_nationkey"),
    "supp_nation": lambda s, d: inst.assignment(s, d, "supplier", "s_suppkey", "s_nationkey"),
    "trade": inst.trade,
}


def cells(spark, d, name: str) -> DataFrame:
    return materialize(MAKE[name](spark, d), name)


def drawn(spark, d, name: str, seed: int = 7) -> DataFrame:
    """The instance with u, written once."""
    return materialize(inst.draw(MAKE[name](spark, d), seed), name)


def u_sql(seed: int = 7) -> str:
    return f"('0x' || substr(md5(concat_ws('|', i, j, {seed})), 1, 8))::BIGINT % 1000000"


def drawn_sql(name: str, seed: int = 7) -> str:
    return f"SELECT i, j, v, {u_sql(seed)} AS u FROM ({SQL[name]}) t"


def product_sql(a: str, b: str, plus: str = "sum({})::BIGINT", times: str = "a.v * b.v", trans=(False, False), more: str = "") -> str:
    ai, ak = ("j", "i") if trans[0] else ("i", "j")
    bk, bj = ("j", "i") if trans[1] else ("i", "j")
    return f"SELECT a.{ai} AS i, b.{bj} AS j, {plus.format(times)} AS v{more.format(k=f'a.{ak}')} FROM {a} a JOIN {b} b ON a.{ak} = b.{bk} GROUP BY 1, 2"


MIN_SQL = {"plus": "min({})", "times": "a.v + b.v"}


def bits_sql(k: str, ell: int = 64) -> str:
    """bit_or of the inner index's bit, as a signed number."""
    x = f"bit_or(1::UBIGINT << ({k} % {ell})::INT)"
    return f"(CASE WHEN {x} >= 9223372036854775808 THEN {x}::HUGEINT - 18446744073709551616 ELSE {x}::HUGEINT END)::BIGINT"


def longs(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.col(n).cast("long") for n in names})
