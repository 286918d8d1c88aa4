import random

import pytest

from setanon.operators import searchsim, threads

from .test_log import log_frame


def brute(queries, docs, n):
    out = {}
    for q in set(queries):
        hits = sorted((-len(set(q.split()) & w), d) for d, w in docs.items() if set(q.split()) & w)
        if hits:
            out[q] = [d for _, d in hits[:n]]
    return out


@pytest.mark.parametrize("few", [496, 0])
def test_lists_are_those_of_brute_force(spark, monkeypatch, few):
    """In blocks of sets and of queries, with words as bits and as strings, and copies of documents."""
    monkeypatch.setattr(searchsim, "FEW", few)
    monkeypatch.setattr(searchsim, "SETS", 40)
    monkeypatch.setattr(searchsim, "QUERIES", 7)
    rnd = random.Random(3)
    vocabulary = [f"w{i}" for i in range(90)]
    docs = {d: set(rnd.choices(vocabulary, range(90, 0, -1), k=rnd.randint(1, 12))) for d in range(150)}
    docs |= {d + 1000: docs[d] for d in range(60)}
    queries = [" ".join(rnd.sample(vocabulary, rnd.randint(1, 5))) for _ in range(25)] + ["none"]
    corpus = spark.createDataFrame([(d, w) for d, ws in docs.items() for w in [*ws, min(ws)]], "doc long, word string")
    got = {r.query: r.docs for r in searchsim.result_lists(spark.createDataFrame([(q,) for q in queries], "query string"), corpus, 8).collect()}
    assert got == brute(queries, docs, 8)


def test_documents_of_one_set_are_matched_once(spark, monkeypatch):
    """A frequent set of words is one row of a block, however many documents hold it."""
    corpus = spark.range(500).selectExpr("id AS doc", "'tea' AS word")
    got = searchsim.result_lists(spark.createDataFrame([("tea",)], "query string"), corpus, 5)
    assert [tuple(r) for r in got.collect()] == [("tea", [0, 1, 2, 3, 4])]


def test_one_pass_cuts_as_the_rounds_do(spark, monkeypatch):
    rnd = random.Random(5)
    names = ["abcd", "abce", "abff", "zzzz", "zzzy", "qqqqqq", "aaaa", "aabb", "aaab"]
    rows = [(f"u{rnd.randrange(6)}", rnd.choice(names)) for _ in range(150)] + [("solo", "abcd")]
    log, o = log_frame(spark, rows), threads.ThreadOptions(edit_threshold=2)
    told = lambda: {(r.user_id, r.at): (r.seq, r.query, r.root) for r in threads.assign_threads(log, o).collect()}
    once = told()
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 4)  # users go on over batches
    try:
        assert told() == once
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    monkeypatch.setattr(threads, "FEW", 2)
    assert told() == once and len(once) == len(rows)


def test_one_pass_needs_no_shuffle_of_pairs(spark):
    """The plan of a log of few queries has one exchange by user and no join of a user's queries."""
    log = log_frame(spark, [("a", "abcd"), ("a", "abce"), ("b", "zzzz")])
    plan = threads.assign_threads(log)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("hashpartitioning(user_id") == 1 and "Join" not in plan
