"""``thread_stats`` makes the threads' ids and keyword sets, and its statistics from them."""

import datetime as dt

from setanon.operators import measures, threads
from setanon.plans import registry


def test_query_makes_thread_sets(spark, monkeypatch):
    made = []

    def sets(rows):
        made.append(threads_sets(rows))
        return made[-1]

    def stats(s):
        made.append(s)
        return thread_stats(s)

    threads_sets, thread_stats = threads.thread_sets, measures.thread_stats
    monkeypatch.setattr(threads, "thread_sets", sets)
    monkeypatch.setattr(measures, "thread_stats", stats)
    row = registry.QUERIES["thread_stats"](spark, "/root/testdata/sf0.001").first()
    assert len(made) == 2 and made[0] is made[1] and {"thread_id", "items", "queries"} <= set(made[0].columns)
    assert row.fewer_threads == 1


def test_sets_of_threads(spark):
    at = dt.datetime(2024, 1, 1)
    rows = [("u", 1, at, 1, "Red bolt", 1), ("u", 2, at, 2, "blue ring", 2), ("u", 3, at, 3, "Red bolt", 1), ("v", 1, at, 1, "red-gear", 1)]
    log = spark.createDataFrame(rows, "user_id string, at int, ts timestamp, seq long, query string, root int")
    got = {(r.user_id, tuple(r["items"])): [tuple(q) for q in r.queries] for r in threads.thread_sets(threads.relabel(log, "k")).collect()}
    assert got == {("u", ("bolt", "red")): [(1, "Red bolt"), (3, "Red bolt")], ("u", ("blue", "ring")): [(2, "blue ring")], ("v", ("gear", "red")): [(1, "red-gear")]}
    st = measures.thread_stats(threads.thread_sets(threads.relabel(log, "k"))).first()
    assert (st.users, st.queries, st.threads, st.avg_keywords) == (2, 4, 3, 2.0)
