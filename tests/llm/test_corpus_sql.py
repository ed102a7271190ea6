"""Every corpus query with SQL gives the rows that DuckDB gives."""

import duckdb
import pytest

from mutualgraph.llm import queries


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(spark, tiny, name):
    duck = duckdb.connect()
    for t in ("documents", "embeddings"):
        duck.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    want = duck.execute(queries.ORACLES[name])
    cols = [d[0] for d in want.description]
    got = queries.QUERIES[name](spark, tiny)
    assert sorted(got.columns) == sorted(cols)
    assert sorted((tuple(r[c] for c in cols) for r in got.collect()), key=repr) == sorted(want.fetchall(), key=repr)
