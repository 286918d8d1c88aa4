"""Copies are counted, not listed: weighted sets give what their records give."""

import random

from pyspark.sql import functions as F

from setanon.operators import baselines, clustering, lsh, majority, measures, records, threads
from setanon.plans.pipeline import AnonOptions, anonymize, cost_curve

SCHEMA = "record_id string, user_id string, items array<string>"


def some(spark, n=120, seed=1):
    r = random.Random(seed)
    rows = [(f"{i:04d}", "u", sorted({r.choice("abcdef") for _ in range(r.randint(1, 3))})) for i in range(n)]
    return spark.createDataFrame(rows, SCHEMA).withColumn("bucket_id", F.element_at("items", 1))


def both(spark):
    recs = some(spark)
    sets = records.weighted(recs.drop("bucket_id")).withColumn("bucket_id", F.element_at("items", 1))
    return recs, sets


def groups(recs):
    return recs.select("record_id", "bucket_id", F.col("bucket_id").alias("group_id"))


def test_lower_bound(spark):
    recs, sets = both(spark)
    near = {}
    rows = recs.collect()
    for x in rows:
        d = sorted(len(set(x.items) ^ set(y.items)) for y in rows if y.record_id != x.record_id and y.bucket_id == x.bucket_id)[:2]
        if d:
            near[x.bucket_id] = near.get(x.bucket_id, 0) + sum(d) / 4
    for table in (recs, sets):
        assert {r.bucket_id: r.bound for r in measures.lower_bound(table, 3, "bucket_id").collect()} == near


def test_bound_makes_no_pairs_of_copies(spark):
    """20,000 copies would be 200 million pairs."""
    recs = spark.range(20_000).select(F.col("id").cast("string").alias("record_id"), F.lit("u").alias("user_id"), F.array(F.lit("a")).alias("items"), F.lit("b").alias("bucket_id"))
    plan = measures.lower_bound(recs, 3, "bucket_id")
    assert [tuple(r) for r in plan.collect()] == [("b", 0.0)]
    assert clustering.medoid(recs, groups(recs)).first().cost == 0


def test_medoid_and_factors(spark):
    recs, sets = both(spark)
    one = {tuple(r) for r in clustering.medoid(recs, groups(recs)).select("group_id", "record_id", "cost").collect()}
    assert one == {tuple(r) for r in clustering.medoid(sets, groups(sets)).select("group_id", "record_id", "cost").collect()}
    rows = recs.collect()
    cost = lambda x: sum(len(set(x.items) ^ set(y.items)) for y in rows if y.bucket_id == x.bucket_id)
    assert all(c == min(cost(x) for x in rows if x.bucket_id == g) for g, _, c in one)
    assert measures.check_factors(recs, groups(recs)).first() == measures.check_factors(sets, groups(sets)).first()


def test_chunk_counts(spark):
    recs, sets = both(spark)
    c, g = F.col("c"), F.col("g")
    told = lambda t: t.agg(F.sum(F.when(2 * c > g, g - c)), F.sum(F.when((2 * c <= g), c))).first()
    for k in (2, 3, 5):
        kept = lsh.split_small(recs, k)[0]
        few = sets.join(kept.select("bucket_id").distinct(), "bucket_id")
        assert told(majority.group_counts(kept, baselines.sorted_chunks(kept, k, "bucket_id"))) == told(baselines.chunk_counts(few, k, "bucket_id"))


def test_cost_curve(spark):
    """Of distinct sets the curve is exactly that of releases; of copies, what ids cannot change, with buckets cut into runs too."""
    recs = some(spark)
    single = recs.dropDuplicates(["items"])
    for table, most in ((single, 2000), (recs, 2000), (recs, 5)):
        o = AnonOptions(bucketing="given", max_bucket=most)
        got = {(r.k, r.metric): r.value for r in cost_curve(table, [2, 3], o).collect()}
        for k in (2, 3):
            want = {r.metric: r.value for r in anonymize(table, k, o).cost.collect()}
            assert {m for kk, m in got if kk == k} == want.keys()
            same = want if table is single else ("records_kept", "records_dropped", "del_small_cluster", "edges_kept")
            assert all(got[k, m] == want[m] for m in same), (k, most, got, want)


def test_keyword_sets(spark):
    log = spark.createDataFrame([("u", 0, 1, "new cars"), ("u", 5, 2, "cars new"), ("v", 0, 3, "new cars"), ("v", 9999, 4, "old")], "user_id string, t int, seq long, query string").withColumn("ts", F.timestamp_seconds("t")).drop("t")
    got = {tuple(r["items"]): (r.record_id, r.weight) for r in threads.keyword_sets(threads.threads_by_gap(log, 60)).collect()}
    assert got == {("cars", "new"): ("u/1", 2), ("old",): ("v/2", 1)}


def copies(spark, n, *more):
    """n records of the set a, b, and single ones of further sets."""
    many = spark.range(n).select(F.format_string("%07d", "id").alias("record_id"), F.lit("u").alias("user_id"), F.split(F.lit("a b"), " ").alias("items"))
    return many.unionByName(spark.createDataFrame([(f"x{i}", "u", s.split()) for i, s in enumerate(more)], SCHEMA)) if more else many


def test_candidates_of_copies(spark):
    """60,000 copies would be 3.6 billion pairs of victims and records."""
    recs = copies(spark, 60_000, "a c")
    from setanon.operators import attacks

    assert tuple(attacks.attack_rate(recs, recs, 2, 2, 0).select("victims", "unique_matches").first()) == (60_001, 1)


def test_rounds_of_copies(spark):
    """20,000 copies would be 200 million pairs; single sets still find a group."""
    from setanon.plans.pipeline import suppress_rounds

    g = suppress_rounds(copies(spark, 20_000, "a c"), 3).groupBy("group_id").count().collect()
    assert [r["count"] for r in g] == [20_001]


def test_facility_of_copies(spark):
    """Copies that no single record needs never reach a kernel; those that it may join do."""
    recs = copies(spark, 3_000, "a b c").withColumn("bucket_id", F.lit("one"))
    r = anonymize(recs, 3, AnonOptions(bucketing="given", solver="facility", max_bucket=9_000))
    sizes = sorted(x["count"] for x in r.groups.groupBy("group_id").count().collect())
    assert sizes == [4, 2_997] and r.edits.count() == 1


def test_log_plans_stay_small(spark):
    """What is read back from a release does not carry the plan that made it, once for each table."""
    from setanon.plans import querylog

    log = spark.createDataFrame([(f"u{i % 9}", i, i, f"new cars {i % 4}") for i in range(90)], "user_id string, t int, seq long, query string").withColumn("ts", F.timestamp_seconds("t")).drop("t")
    r = querylog.anonymize_log(log, 3, querylog.LogOptions("k", split="gap", gap_seconds=60, anon=AnonOptions(p=1), canonicalize=True))
    assert len(r.audit_literal(3)._jdf.queryExecution().toString()) < 200_000


def test_log_cost_is_that_of_the_log(spark):
    """Copies of threads are counted; the cost is that of the run that lists them."""
    import datetime as dt

    from setanon.plans.querylog import LogOptions, anonymize_log, log_cost

    words = ["red car", "red cars now", "blue sky", "blue sky map", "tax form"]
    day = lambda n: dt.datetime(2020, 1, 1) + dt.timedelta(days=n)
    rows = [(f"u{u}", day(i), u * 10 + i, words[(u * i + i) % 5 if u % 3 else i]) for u in range(12) for i in range(5)]
    log = spark.createDataFrame(rows, "user_id string, ts timestamp, seq long, query string")
    for split in ("topics", "sessions"):
        o = LogOptions("k", split=split, anon=AnonOptions(p=1))
        got = {r.metric: r.value for r in log_cost(log, 3, o).collect()}
        r = anonymize_log(log, 3, o)
        want = {x.metric: x.value for x in r.result.cost.collect()}
        assert got.pop("edges") == r.threads.agg(F.sum(F.size("items"))).first()[0]
        for metric in ("total", "records_kept", "records_dropped", "edges_kept", "del_small_cluster"):
            assert got[metric] == want[metric], (split, metric)


def test_search_is_whole(spark):
    """Every query against every record, over more places than one word of bits holds."""
    import random

    from setanon.operators.distance import search

    rng = random.Random(3)
    sets = {str(i): sorted(rng.sample(range(130), rng.randint(0, 12))) for i in range(60)} | {"60": [129], "61": [63, 64], "62": [63, 64]}
    v = spark.createDataFrame(list(sets.items()), "record_id string, places array<int>")
    got = {(r.a, r.b): (r.common, r.d) for r in search(v.where("record_id % 20 = 0"), v).collect()}
    want = {(a, b): (len(set(x) & set(y)), len(set(x) ^ set(y))) for a, x in sets.items() for b, y in sets.items() if int(a) % 20 == 0 and a != b and set(x) & set(y)}
    assert got == want
