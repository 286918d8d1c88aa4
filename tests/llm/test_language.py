import zlib

import numpy as np

from setanon.llm import language as lg


def test_em_recovers_shares():
    rnd = np.random.default_rng(0)
    p = rnd.dirichlet(np.full(400, 0.3), 3).T + 1e-9
    p /= p.sum(axis=0)
    c = rnd.multinomial(20_000, p @ [0.7, 0.3, 0.0]).astype(float)
    use = c > 0
    shares = lg.infer(p[use], c[use], lg.Options())
    assert set(shares) == {0, 1} and abs(shares[0] - 0.7) < 0.03
    one = rnd.multinomial(3000, p[:, 2]).astype(float)
    assert set(lg.infer(p[one > 0], one[one > 0], lg.Options())) == {2}


def test_em_likelihood_equals_grid_search():
    rnd = np.random.default_rng(1)
    p = rnd.dirichlet(np.ones(30), 2).T
    c = rnd.integers(1, 9, 30).astype(float)
    share, fit = lg.em(p, c, 500)
    best = max(float(c @ np.log(p @ [a, 1 - a])) for a in np.linspace(1e-6, 1 - 1e-6, 2001))
    assert abs(fit - best) < 1e-3


def test_held_out_accuracy(spark):
    truth = {r.doc_id: r.lang for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()}
    rows = lg.op1_language(spark, "/root/testdata/sf0.01").collect()
    assert len(rows) == len(truth)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    held = [r for r in rows if r.held_out]
    assert np.mean([r.lang_pred == truth[r.doc_id] for r in held]) > 0.98
    assert all(0 <= r.score <= 1 for r in rows)


def test_edges(spark):
    rows = [(1, "the cat and the dog", "en"), (2, None, "en"), (3, "le chat et le chien", "fr"), (None, "der Hund", "de"), (4, "12 34 %%", None), (5, "", "fr"), (5, "mot " * 30_000, None)]
    df = spark.createDataFrame([(a, b, c, 0.0) for a, b, c in rows], "doc_id long, text string, lang string, score double")
    m = lg.learn(df.where("doc_id IS NOT NULL").select("text", "lang"))
    assert m.langs == ("en", "fr")
    out = lg.predict(df, m).collect()
    assert len(out) == 7
    assert [r.lang_pred for r in out if r.doc_id in (2, 4)] == ["und", "und"]
    assert {r.lang_pred for r in out if r.doc_id == 5} == {"und", "fr"}
    none = lg.learn(df.limit(0).select("text", "lang"))
    assert {r.lang_pred for r in lg.predict(df, none).collect()} == {"und"}
    assert lg.predict(df.limit(0), m).count() == 0
    mix = m.mixture("the cat and the dog " * 20 + "le chat et le chien " * 20)
    assert {k for k, _ in mix} == {"en", "fr"}
