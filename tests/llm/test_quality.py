import numpy as np
import pytest
from pyspark.sql import functions as F

from setanon.llm import quality as q
from setanon.llm.words import WordHasher

H = WordHasher(punctuation_is_space=True)


def test_fit_recovers_order_and_thresholds():
    rnd = np.random.default_rng(2)
    words = [f"word{i}" for i in range(60)]
    texts, grade = [], []
    for _ in range(1500):
        bad, mid = rnd.random() < 0.2, rnd.random() < 0.3
        t = list(rnd.choice(words, 30)) + ["vile"] * bad + ["meh"] * (mid and not bad)
        texts.append(" ".join(t).encode())
        grade.append(0 if bad else 1 if mid else 2)
    ids, at = q.features(texts, H)
    m = q.fit(ids, at, np.asarray(grade))
    assert m.cuts[0] < m.cuts[1]
    tail = m.tails(m.scores(texts, H))
    assert (tail[:, 0] >= tail[:, 1]).all()
    guess = (tail >= 0.5).sum(axis=1)
    assert (guess == grade).mean() > 0.98


def test_scores_equal_plain_sum():
    texts = [b"a b c a", b"", b"LOUD words!!", "été".encode()]
    ids, at = q.features(texts, H)
    bucket = np.unique(ids)
    m = q.Model(bucket, np.arange(len(bucket), dtype=np.float32), np.asarray([0.0, 1.0]))
    for i, t in enumerate(texts):
        mine = ids[at[i] : at[i + 1]]
        assert m.scores(texts, H)[i] == pytest.approx(sum(np.searchsorted(bucket, x) for x in mine))
        assert len(set(mine.tolist())) == len(mine)


def test_held_out_labels(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    model = q.train(docs, labels.where("doc_id % 4 <> 0"))
    held = q.graded(labels).where("doc_id % 4 = 0")
    r = q.scored(docs, model).join(held, "doc_id").groupBy("grade").agg(F.avg(F.col("_rated.kept").cast("int")).alias("kept")).collect()
    kept = {x.grade: x.kept for x in r}
    assert kept[2] > 0.98 and kept[0] < 0.05 and kept[1] < 0.05


def test_edges(spark):
    rows = [(1, None), (1, "fine words here"), (None, ""), (2, "x" * 200_000)]
    docs = spark.createDataFrame([(a, b, 3) for a, b in rows], "doc_id long, text string, quality int")
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    out = q.select_good(docs, none)
    assert out.columns == docs.columns and out.count() == 4
    odd = spark.createDataFrame([(1, None, None), (None, 1, 0), (2, None, 1), (2, 1, 0), (1, 1, None)], "doc_id long, quality int, toxic int")
    assert {(r.doc_id, r.grade) for r in q.graded(odd).collect()} == {(1, 2), (2, 0)}
    assert q.scored(docs, q.train(docs, odd)).count() == 4
    assert q.select_good(docs.limit(0), odd).count() == 0


def test_fit_sample_is_not_cut_for_memory():
    assert q.Options().max_rows == 12_000


def test_sample_is_bounded_and_ids_count_once(spark):
    docs = spark.createDataFrame([(i % 50, f"text {i}", 1) for i in range(400)], "doc_id long, text string, grade int")
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(50)], "doc_id long, quality int, toxic int")
    assert [len(q.sample(docs, q.graded(labels), q.Options(max_rows=m))[2]) for m in (20, 500)] == [20, 50]
    clash = docs.withColumn("_rated", F.lit("mine"))
    out = q.select_good(clash, labels)
    assert out.columns == clash.columns and {r["_rated"] for r in out.collect()} <= {"mine"}
