"""Every named query against its SQL, on the smallest tables."""

import math

import duckdb
import pandas as pd
import pytest

from deltamat import catalog

SLOW = {"dyn_alg_ten_batches", "dyn_gen_ten_batches"}
NAMES = sorted(set(catalog.queries()) - SLOW)


def normal(df: pd.DataFrame) -> list:
    def one(x):
        if x is None or x is pd.NA or x is pd.NaT or (isinstance(x, float) and math.isnan(x)):
            return None
        if isinstance(x, pd.Timestamp):
            return x.isoformat()
        return x.item() if hasattr(x, "item") else x

    cols = sorted(df.columns)
    rows = [tuple(one(x) for x in r) for r in df[cols].itertuples(index=False, name=None)]
    return sorted(rows, key=repr)


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


def floats(rows):
    return [tuple(round(float(x), 9) if isinstance(x, (int, float)) and not isinstance(x, bool) else x for x in r) for r in rows]


@pytest.mark.parametrize("name", NAMES)
def test_query(spark, sf, duck, name):
    got = catalog.queries()[name](spark, sf).toPandas()
    sql = catalog.oracle_sql().get(name)
    if sql is None:
        assert len(got)
    else:
        want = duck.sql(sql).df()
        assert sorted(got.columns) == sorted(want.columns)
        assert sorted(floats(normal(got)), key=repr) == sorted(floats(normal(want)), key=repr)


def test_flagship(spark, sf):
    assert catalog.flagship(spark, sf).count() > 0
