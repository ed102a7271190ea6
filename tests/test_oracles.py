"""Every query with SQL gives the rows that DuckDB gives."""

import math

import duckdb
import pytest

import __spark_entry__ as entry
from mutualgraph import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Larger networks make these slow here; the smaller network's twins cover them.
SLOW = {"closeness_matrix_net1", "common_neighbors", "combined_ndbi_rand", "combined_sil_mi", "silhouette_net2"}


@pytest.fixture(scope="module")
def duck(tiny):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    return c


def canonical(v):
    if isinstance(v, bool) or v is None or isinstance(v, str):
        return v
    try:
        f = float(v)
        return None if math.isnan(f) else round(f, 5) + 0.0
    except (TypeError, ValueError):
        return str(v)


@pytest.mark.parametrize("name", sorted(set(registry.ORACLES) - SLOW))
def test_query_equals_sql(spark, duck, tiny, name):
    got = registry.QUERIES[name](spark, tiny)
    want = duck.execute(registry.ORACLES[name])
    cols = [d[0] for d in want.description]
    assert sorted(cols) == sorted(got.columns)
    order = [cols.index(c) for c in sorted(cols)]
    a = sorted((tuple(canonical(r[c]) for c in sorted(cols)) for r in got.collect()), key=repr)
    b = sorted((tuple(canonical(r[i]) for i in order) for r in want.fetchall()), key=repr)
    assert len(a) == len(b)
    for x, y in zip(a, b, strict=True):
        assert all(p == q or (isinstance(p, float) and isinstance(q, float) and abs(p - q) < 3e-5) for p, q in zip(x, y, strict=True)), (x, y)


def test_contract():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    got = entry.entry(spark)
    assert got.columns == ["net", "user_id", "cluster"] and got.count() == 320
