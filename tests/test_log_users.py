import datetime as dt

from pyspark.sql import functions as F

from setanon.operators import measures, threads
from setanon.plans.querylog import LogOptions, solve_log


def test_threads_are_folded_where_they_are_cut(spark):
    t0 = dt.datetime(2024, 1, 1)
    rows = [(u, t0 + dt.timedelta(minutes=i), i, q) for i, (u, q) in enumerate([(u, q) for u in "abcdefg" for q in ("red ring", "red rind", None, "old plate", "red ring", u + u + " box of many")])]
    log = spark.createDataFrame(rows, "user_id string, ts timestamp, seq long, query string")
    want = threads.assign_threads(log).groupBy("user_id", "root").agg(F.sort_array(F.collect_set("query")).alias("q"), F.count(F.lit(1)).alias("n"))
    got = threads.distinct_queries(log)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    told, r = solve_log(log, 3, LogOptions("k"))
    assert "queries" not in told.columns and told.agg(F.sum("n")).first()[0] == 35
    ids = {x.record_id for x in r.groups.collect()} | {x.record_id for x in r.dropped.collect()}
    assert ids == {x.record_id for x in told.collect()} and r.groups.count() >= 14
    assert measures.audit(r.records, 3, "user").first().violations == 0
