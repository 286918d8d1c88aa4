import datetime as dt
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from setanon.operators import baselines, kernel, lsh, materialize, threads
from setanon.operators.kernel import SolveOptions
from setanon.plans.pipeline import AnonOptions
from setanon.plans.querylog import LogOptions, anonymize_log


def test_exhaustive_candidates_raise_above_their_bound():
    data = [[f"x{i}", f"y{i % 3}"] for i in range(16)]
    ids = [f"r{i}" for i in range(16)]
    with pytest.raises(ValueError, match="exhaustive"):
        kernel.solve(ids, ids, data, SolveOptions(3, candidates="exhaustive"))


def brute_facility(d, price):
    """Opening by opening, every facility priced anew."""
    n, price = len(d), price.astype(float).copy()
    serve, free = np.full(n, -1), set(range(n))
    while free:
        best = None
        for j in range(n):
            mine = sorted(free, key=lambda i: (d[j, i], i))
            for s in range(1, len(mine) + 1):
                key = (round((price[j] + sum(d[j, i] for i in mine[:s])) / s, 9), j)
                if best is None or key < best[0]:
                    best = (key, mine[:s])
        (_, j), mine = best
        serve[mine], price[j] = j, 0
        free -= set(mine)
    opened = np.unique(serve)
    return opened[d[:, opened].argmin(axis=1)]


def test_lazy_facility_equals_plain():
    rnd = np.random.default_rng(0)
    for _ in range(25):
        d = kernel.distances((rnd.random((12, 9)) < 0.4).astype(np.float32))
        price = kernel.opening_price(d, 3, 0.5)
        assert kernel.facility_greedy(d, price).tolist() == brute_facility(d, price).tolist()


def test_local_search_ends_where_no_move_helps():
    rnd = np.random.default_rng(1)
    for _ in range(25):
        d = kernel.distances((rnd.random((11, 8)) < 0.4).astype(np.float32)).astype(float)
        price = kernel.opening_price(d, 2, 0.5)
        o = sorted(set(kernel.facility_local_search(d, price).tolist()))
        total = lambda o: price[o].sum() + d[:, o].min(axis=1).sum()
        rest = [j for j in range(11) if j not in o]
        moves = [o + [j] for j in rest] + [[y for y in o if y != x] for x in o if len(o) > 1] + [[y for y in o if y != x] + [j] for x in o for j in rest]
        assert all(total(m) >= total(o) - 1e-6 for m in moves)


def log_frame(spark, rows):
    t0 = dt.datetime(2024, 1, 1)
    return spark.createDataFrame([(u, t0 + dt.timedelta(days=31 * (i % 3)), i, q) for i, (u, q) in enumerate(rows)], "user_id string, ts timestamp, seq long, query string")


def test_attributes_are_a_column_and_never_in_the_text(spark):
    rnd = random.Random(1)
    log = log_frame(spark, [(f"u{i % 30}", rnd.choice(["red apple", "green apple", "blue pear"])) for i in range(120)])
    r = anonymize_log(log, 3, LogOptions("s", split="sessions", anon=AnonOptions(p=1), attributes=(("month", F.date_format("ts", "yyyy-MM")),)))
    out = r.released.collect()
    assert out and not any(":" in x.query for x in out)
    assert any(x.attributes for x in out) and all(a.startswith("month:") for x in out for a in x.attributes)
    assert r.audit_literal(3).first().violations == 0


def test_dates_of_equal_digits_stay_apart(spark):
    recs = spark.createDataFrame([("r", "u", ["day:2024-01-12", "day:2024-02-11", "tea", "eat"])], "record_id string, user_id string, items array<string>")
    tokens = {x.keyword: x.token for x in lsh.tokenize(recs)[1].collect()}
    assert tokens["day:2024-01-12"] != tokens["day:2024-02-11"] and tokens["tea"] == tokens["eat"]


def test_logs_hide_a_user_among_other_users(spark):
    log = log_frame(spark, [("ann", "pine straw")] * 4 + [("bob", "pine straw"), ("cal", "green tea"), ("dee", "green tea"), ("eve", "green tea")])
    assert LogOptions("s").anon.unit == "user"
    r = anonymize_log(log, 3, LogOptions("s", split="singletons"))
    assert {x.query for x in r.released.collect()} == {"green tea"}


def test_rewriting_equals_plain(spark):
    rnd = random.Random(3)
    words = ["ab", "cd", "ef", "gh"]
    data, edits = [], []
    for i in range(40):
        queries = [(10 * j, " ".join(rnd.choices(words, k=rnd.randint(1, 4)))) for j in range(rnd.randint(1, 3))]
        data.append((f"t{i}", "u", queries))
        held = {w for _, q in queries for w in q.split()}
        edits += [(f"t{i}", w, "del") for w in held if rnd.random() < 0.4] + [(f"t{i}", w, "add") for w in ("new", "zz") if rnd.random() < 0.4]
    df = spark.createDataFrame(data, "thread_id string, user_id string, queries array<struct<seq:long,query:string>>")
    got = {r.thread_id: [(q.seq, q.query) for q in r.queries] for r in materialize.rewrite_queries(df, spark.createDataFrame(edits, "record_id string, item string, op string")).collect()}
    for t, _, queries in data:
        gone, new = {w for r, w, op in edits if (r, op) == (t, "del")}, sorted(w for r, w, op in edits if (r, op) == (t, "add"))
        want = []
        for j, (seq, q) in enumerate(queries):
            text = " ".join([w for w in q.split() if w not in gone] + (new if j == 0 else []))
            want += [(seq, text)] if text else []
        assert got[t] == want


def test_a_hot_bucket_loses_nothing(spark):
    recs = spark.range(6000).select(F.col("id").cast("string").alias("record_id"), F.col("id").cast("string").alias("user_id"), F.when(F.col("id") % 2 == 0, F.array(F.lit("a"), F.concat(F.lit("x"), (F.col("id") % 700).cast("string")))).otherwise(F.array(F.concat(F.lit("y"), (F.col("id") % 40).cast("string")))).alias("items"))
    b = recs.withColumn("bucket_id", F.element_at("items", 1))
    kept, small = lsh.split_small(b, 3, keep_size=True)
    parts = lsh.refine(kept, 500, 2, k=3)
    sizes = [r["count"] for r in parts.groupBy("bucket_id").count().collect()]
    assert sum(sizes) + small.count() == 6000 and max(sizes) < 1000 and min(sizes) >= 3


def test_suppression_with_stars(spark):
    recs = spark.createDataFrame([("1", "u", ["a", "b"]), ("2", "u", ["a"]), ("3", "u", ["c"])], "record_id string, user_id string, items array<string>")
    groups = spark.createDataFrame([("1", "g"), ("2", "g"), ("3", "h")], "record_id string, group_id string")
    assert {(r.group_id, tuple(r["items"]), r.stars) for r in baselines.suppress_only(recs, groups).collect()} == {("g", ("a",), 2), ("h", ("c",), 0)}


def test_threads_of_either_similarity_join(spark):
    log = log_frame(spark, [("u", "tea pot"), ("u", "kettle on"), ("u", "tea pots"), ("u", "zzz")])
    corpus = spark.createDataFrame([(1, "tea"), (1, "kettle"), (2, "pot"), (2, "on"), (3, "zzz")], "doc long, word string")
    by = lambda o: len({r.root for r in threads.assign_threads(log, o, corpus).collect()})
    edit, results = threads.ThreadOptions(edit_threshold=2), threads.ThreadOptions(similarity="results", top=5, min_overlap=2)
    both = threads.ThreadOptions(edit_threshold=2, similarity="any", top=5, min_overlap=2)
    assert by(both) <= min(by(edit), by(results)) and by(both) == 2
