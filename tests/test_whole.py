"""The queries over whole tables that have no SQL, against brute force on small tables."""

import datetime
import random
import re
from collections import Counter

import pytest

from deltamat import catalog


@pytest.fixture(scope="module")
def small(spark, tmp_path_factory):
    rng = random.Random(5)
    d = str(tmp_path_factory.mktemp("whole"))
    texts = ["same few words here"] * 25 + [" ".join(rng.choice("the cat dog Sun moon 7".split()) for _ in range(6)) for _ in range(10)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1).write.parquet(f"{d}/documents.parquet")
    users = [rng.randrange(9) for _ in range(14)] + [20, 21, 22, 20]
    t = datetime.datetime(2024, 1, 1)
    spark.createDataFrame([(k, u, t, "{}") for k, u in enumerate(users)], "event_id long, user_id long, ts timestamp, props string").coalesce(1).write.parquet(f"{d}/events.parquet")
    return d, texts, users


def test_similarity_of_all_terms(spark, small):
    d, texts, _ = small
    m = [Counter(re.findall("[a-z0-9]+", t.lower())) for t in texts]
    want = {(a, b): n for a in range(len(m)) for b in range(a + 1, len(m)) if (n := sum(m[a][w] * m[b][w] for w in m[a])) >= 3}
    assert {(r.i, r.j): r.v for r in catalog.queries()["app_doc_similarity_whole"](spark, d).collect()} == want
    assert want[0, 24] == 4


def levels(users):
    g = {}
    for a, b in zip(users, users[1:], strict=False):
        g.setdefault(a, set()).add(b)
    return g


def test_levels_over_all_edges(spark, small):
    d, _, users = small
    g, want = levels(users), {}
    for a in g:
        if g[a] - {a}:
            front = {a}
            for v in range(7):
                for x in front:
                    want.setdefault((a, x), v)
                front = {y for x in front for y in g.get(x, ()) if (a, y) not in want}
    assert {(r.i, r.j): r.v for r in catalog.queries()["app_bfs_levels_whole"](spark, d).collect()} == want


def test_closure_over_all_edges(spark, small):
    d, _, users = small
    g, want = levels(users), set()
    for a in g:
        todo = list(g[a])
        while todo:
            x = todo.pop()
            if (a, x) not in want:
                want.add((a, x))
                todo += g.get(x, ())
    assert {(r.i, r.j) for r in catalog.queries()["closure_reachability_whole"](spark, d).collect()} == want


@pytest.mark.parametrize("name", ["rmat_edges", "grid_balance_perm", "grid_balance_plain"])
def test_power_law_graphs_have_an_edge_for_every_event(spark, small, name):
    d, _, users = small
    r = catalog.queries()[name](spark, d).collect()
    assert {x.e for x in r} == set(range(len(users))) if name == "rmat_edges" else 1 <= r[0].most <= len(users) and r[0].mean <= len(users) / 16


def test_bounds_follow_the_given_tables(spark, tmp_path):
    d = str(tmp_path)
    spark.createDataFrame([(k, k % 3) for k in range(40)], "o_orderkey long, o_custkey long").write.parquet(f"{d}/orders.parquet")
    spark.createDataFrame([(k, k % 2) for k in range(3)], "c_custkey long, c_nationkey int").write.parquet(f"{d}/customer.parquet")
    got = {r.method: r for r in catalog.queries()["cost_bounds"](spark, d).collect()}
    assert (got["static"].bandwidth, got["static"].work, got["static"].memory) == (43 / 8, 40 / 64, 40 / 64)
