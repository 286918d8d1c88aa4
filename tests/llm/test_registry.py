import os

import duckdb
import pytest

from setanon.llm import registry

DIR = os.environ.get("SETANON_TEST_DIR", "/root/testdata/sf0.001")


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(spark, name):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM '{DIR}/documents.parquet'")
    q = c.execute(registry.oracle_sql()[name])
    cols = sorted(x[0] for x in q.description)
    names = [x[0] for x in q.description]
    want = sorted(tuple(r[names.index(k)] for k in cols) for r in q.fetchall())
    df = registry.queries()[name](spark, DIR)
    assert sorted(df.columns) == cols
    assert sorted(tuple(r[k] for k in cols) for r in df.collect()) == want
