"""Every query of the catalogue against its SQL, on the smallest tables."""

import duckdb
import pytest

from bundlemv.plans import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Long loops whose methods other tests run.
SLOW = {"rank_until_settled"}


@pytest.fixture(scope="module")
def con(tiny):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as from '{tiny}/{t}.parquet'")
    return c


def near(a, b):
    if isinstance(a, float) and isinstance(b, float):
        return abs(a - b) <= 1e-9 * max(1.0, abs(a), abs(b))
    return a == b


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - SLOW))
def test_query(spark, con, tiny, name):
    df = catalog.QUERIES[name](spark, tiny)
    cols = sorted(df.columns)
    key = lambda r: tuple((x is None, x if x is not None else 0) for x in r)
    got = sorted((tuple(r[c] for c in cols) for r in df.collect()), key=key)
    if name not in catalog.SQL:
        assert got
        return
    out = con.execute(catalog.SQL[name])
    names = [d[0] for d in out.description]
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    want = sorted((tuple(r[i] for i in at) for r in out.fetchall()), key=key)
    assert len(got) == len(want)
    assert all(near(x, y) for g, w in zip(got, want) for x, y in zip(g, w))
