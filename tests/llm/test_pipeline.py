import os

import pytest

pytest.importorskip("corpus_pipeline")

import corpus_pipeline as cp

DIR = "/root/testdata/sf0.001"


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    n = docs.count()
    for name, stage in cp.STAGES[:-1]:
        out = stage(spark, docs, DIR)
        assert out.columns == docs.columns and out.dtypes == docs.dtypes, name
        m = out.count()
        assert 0 < m <= n, name
        docs = out
    last = cp.STAGES[-1][1](spark, docs, DIR)
    assert {r.doc_id for r in last.select("doc_id").collect()} == {r.doc_id for r in docs.select("doc_id").collect()}
    assert cp.run(spark, DIR).count() == last.count()


def test_odd_rows_pass(spark, tmp_path):
    docs = spark.createDataFrame([(1, None, "en", "s", 0, 2), (None, "some words", None, "s", 0, 3), (None, "some words", None, None, None, 4)], "doc_id long, text string, lang string, source string, n_chars long, length int")
    d = str(tmp_path)
    docs.write.parquet(f"{d}/documents.parquet")
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{DIR}/{t}.parquet").limit(0).write.parquet(os.path.join(d, f"{t}.parquet"))
    rows = cp.run(spark, d).collect()
    assert sorted((r.doc_id is None, r.length) for r in rows) == [(False, 1), (True, 3)]
    docs.limit(0).write.mode("overwrite").parquet(f"{d}/documents.parquet")
    assert cp.run(spark, d).count() == 0
