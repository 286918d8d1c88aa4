"""Edits, spelling and attributes read off threads beside their solution are those of the joins."""

import datetime as dt
import random

from pyspark.sql import functions as F

from setanon.functions.sets import is_word
from setanon.operators import lsh, materialize, threads
from setanon.plans.pipeline import AnonOptions
from setanon.plans.querylog import LogOptions, anonymize_log, log_cost


def test_as_by_joins(spark):
    rnd = random.Random(3)
    names = ["red bolt", "red blot", "old plate", "blue ring", "blue grin ring", "bolt red plate"]
    rows = [(f"u{i % 12}", dt.datetime(2024, 1 + i % 3, 1 + rnd.randrange(25)), i, rnd.choice(names)) for i in range(160)]
    log = spark.createDataFrame(rows, "user_id string, ts timestamp, seq long, query string")
    o = LogOptions("k", split="gap", gap_seconds=86400, anon=AnonOptions(p=1), canonicalize=True, attributes=(("month", F.date_format("ts", "MM")),))
    r = anonymize_log(log, 3, o)
    told = lambda df: sorted(map(tuple, df.collect()))
    own = {x.thread_id: set(x["items"]) for x in r.threads.collect()}
    cut = threads.relabel(threads.threads_by_gap(log, 86400), "k").join(log.select("seq", F.concat(F.lit("month:"), F.date_format("ts", "MM")).alias("m")), "seq")
    months = {x.thread_id: set(x.m) for x in cut.groupBy("thread_id").agg(F.collect_set("m").alias("m")).collect()}
    assert {t: {x for x in s if ":" in x} for t, s in own.items()} == months
    tokens = lsh.tokenize(r.threads.select(F.col("thread_id").alias("record_id"), "user_id", "items"))[1]
    edits = materialize.lift_edits(r.result.edits, r.threads, r.result.groups, tokens)
    assert told(r.edits.select("record_id", "item", "op")) == told(edits) != []
    kept = r.threads.join(r.result.groups.select(F.col("record_id").alias("thread_id")), "thread_id", "left_semi")
    assert told(r.attributes) == told(materialize.edited_attributes(kept, edits))
    stand = materialize.cluster_keywords(r.threads, r.result.groups, tokens)
    spell = kept.select(F.col("thread_id").alias("record_id"), F.explode("items").alias("keyword")).join(tokens, "keyword").join(r.result.groups.select("record_id", "bucket_id"), "record_id")
    canon = spell.where(is_word(F.col("keyword"))).join(stand.withColumnRenamed("keyword", "to"), ["bucket_id", "token"]).select("record_id", "keyword", "to")
    want = materialize.rewrite_queries(kept, edits, canon)
    assert told(r.rewritten.select("thread_id", "queries")) == told(want.select("thread_id", "queries"))
    assert set(r.released.columns) == {"thread_id", "seq", "query", "attributes"}
    assert not any("\x1f" in x.group_id + x.record_id for x in r.result.groups.collect())


def test_tokens_are_looked_up_in_place(spark):
    recs = spark.createDataFrame([("a", "u", ["listen", "month:1", "red"], 7), ("b", "u", ["silent"], 8), ("c", "v", [], 9)], "record_id string, user_id string, items array<string>, more int")
    near, far = (lsh.tokenize(recs, small=s)[0] for s in (10, 0))
    got = sorted((r.record_id, tuple(r["items"]), r.more) for r in near.collect())
    assert got == sorted((r.record_id, tuple(r["items"]), r.more) for r in far.collect()) and [x[0] for x in got] == ["a", "b"]
    assert "Exchange hashpartitioning(record_id" not in near._jdf.queryExecution().executedPlan().toString()


def test_log_cost_keeps_weights(spark):
    rows = [(f"u{i % 9}", dt.datetime(2024, 1, 1 + i % 20), i, ("red bolt", "old plate", "blue ring")[i % 3]) for i in range(60)]
    log = spark.createDataFrame(rows, "user_id string, ts timestamp, seq long, query string")
    cost = {r.metric: r.value for r in log_cost(log, 3, LogOptions("k", split="gap", anon=AnonOptions(p=1))).collect()}
    assert cost["edges"] == cost["edges_kept"] + cost["del_small_cluster"] > 0
