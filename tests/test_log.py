import datetime as dt
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from setanon.operators import attacks, baselines, lsh, measures, threads, utility
from setanon.operators.searchsim import overlapping, top_results
from setanon.plans.pipeline import AnonOptions
from setanon.plans.querylog import LogOptions, anonymize_log, explain_user
from setanon.plans.registry import QUERIES
from setanon.sources import tables

DIR = "/root/testdata/sf0.001"


def log_frame(spark, rows):
    t0 = dt.datetime(2024, 1, 1)
    return spark.createDataFrame([(u, t0 + dt.timedelta(minutes=i), i, q) for i, (u, q) in enumerate(rows)], "user_id string, ts timestamp, seq long, query string")


MINI = (
    [("ann", q) for q in ["pine straw smalltown", "pine straw smalltwon", "effects of tea", "efects of tea", "doe family reunion"]]
    + [(u, "pine straw mulch") for u in ("bob", "cal", "dee")]
    + [(u, "effects of tea") for u in ("bob", "cal", "eve")]
)


def test_first_pass_and_collapse(spark):
    log = log_frame(spark, [("a", "abcd"), ("a", "zzzz"), ("a", "abce"), ("a", "zzzy"), ("a", "qqqqqqq"), ("b", "abcd")])
    o = threads.ThreadOptions(edit_threshold=2)
    sim = threads.similar_queries(log, o)
    got = {(r.user_id, r.query): r.root for r in threads.first_pass(log, sim).collect()}
    assert got == {("a", "abcd"): 1, ("a", "zzzz"): 2, ("a", "abce"): 1, ("a", "zzzy"): 2, ("a", "qqqqqqq"): 5, ("b", "abcd"): 1}
    # a later query may bring two neighbouring threads together
    chain = log_frame(spark, [("a", "aaaa"), ("a", "aabb"), ("a", "aaab")])
    sim = threads.similar_queries(chain, o)
    assert {r.query: r.root for r in threads.first_pass(chain, sim).collect()} == {"aaaa": 1, "aabb": 2, "aaab": 2}
    assert {r.root for r in threads.collapse(threads.first_pass(chain, sim), sim).collect()} == {1}


def test_relational_threads_equal_kernel(spark):
    log = tables.order_log(spark, DIR).where("cast(user_id as int) % 5 = 0")
    sim = threads.similar_queries(log).cache()
    a = {(r.user_id, r.at): r.root for r in threads.assign_threads(log).collect()}
    b = {(r.user_id, r.at): r.root for r in threads.assign_threads_kernel(log, sim).collect()}
    assert a == b and len(a) == log.count()


def test_other_splits(spark):
    log = log_frame(spark, MINI)
    assert threads.sessions(log).select("user_id", "root").distinct().count() == 5
    assert threads.threads_singleton(log).select("user_id", "root").distinct().count() == len(MINI)
    assert threads.threads_by_gap(log, 30).select("user_id", "root").distinct().count() == len(MINI)
    assert threads.threads_by_gap(log, 10**6).select("user_id", "root").distinct().count() == 5
    ids = threads.relabel(threads.assign_threads(log), "s1").select("thread_id").distinct()
    other = threads.relabel(threads.assign_threads(log), "s2").select("thread_id").distinct()
    assert ids.join(other, "thread_id").count() == 0


def test_search_overlap(spark):
    corpus = spark.createDataFrame([(d, w) for d, t in enumerate(["a b", "a c", "b c", "a", "d"]) for w in t.split()], "doc long, word string")
    q = spark.createDataFrame([("a b",), ("b a",), ("d",), ("x",)], "query string")
    top = defaultdict(list)
    for r in top_results(q, corpus, 2).orderBy("place").collect():
        top[r.query].append(r.doc)
    assert dict(top) == {"a b": [0, 1], "b a": [0, 1], "d": [4]}
    assert [tuple(r) for r in overlapping(top_results(q, corpus, 2), 2).collect()] == [("a b", "b a", 2)]
    log = log_frame(spark, [("u", "a b"), ("u", "b a")])
    o = threads.ThreadOptions(similarity="results", top=2, min_overlap=2)
    assert {r.root for r in threads.assign_threads(log, o, corpus).collect()} == {1}


def test_mini_log(spark):
    o = LogOptions("secret", threads=threads.ThreadOptions(edit_threshold=3), anon=AnonOptions(p=1, popular_first=True))
    r = anonymize_log(log_frame(spark, MINI), 3, o)
    view = {x.before: x for x in explain_user(r, "ann").collect()}
    assert view["doe family reunion"].after is None
    assert view["effects of tea"].after == "effects of tea"
    first = view["pine straw smalltown"]
    if first.after is not None:
        assert "smalltown" in first.deleted and "smalltown" not in first.after
    out = r.released.collect()
    assert all(len(x.thread_id) == 64 for x in out) and set(r.released.columns) == {"thread_id", "seq", "query"}
    words = " ".join(x.query for x in out)
    assert "doe" not in words and "smalltown" not in words
    cost = {x.metric: x.value for x in r.cost.collect()}
    assert cost["keywords_del_small_cluster"] >= 3


def test_log_is_anonymous(spark):
    log = tables.order_log(spark, DIR)
    for o in (LogOptions("s", anon=AnonOptions(p=2), canonicalize=True), LogOptions("s", anon=AnonOptions(p=2, unit="user"), identity="exact"), LogOptions("s", split="sessions", anon=AnonOptions(p=1))):
        r = anonymize_log(log, 3, o)
        unit = o.anon.unit
        assert measures.audit(r.result.records, 3, unit).first().violations == 0
        if o.canonicalize or o.identity == "exact":
            full = r.records.where(F.size("items") > 0)
            assert measures.audit(full, 3, unit).first().violations == 0
        before = {x.record_id for x in r.result.groups.collect()}
        assert before | {x.record_id for x in r.result.dropped.collect()} == {x.thread_id for x in r.threads.collect()}


def test_attributes_become_items(spark):
    log = tables.order_log(spark, DIR)
    o = LogOptions("s", anon=AnonOptions(p=1), attributes=(("month", F.date_format("ts", "yyyy-MM")),))
    r = anonymize_log(log, 2, o)
    items = {x for row in r.threads.collect() for x in row["items"]}
    assert any(x.startswith("month:") for x in items) and measures.audit(r.result.records, 2).first().violations == 0


def rec_frame(spark, sets, users=None):
    return spark.createDataFrame([(f"r{i}", (users or {}).get(i, f"u{i}"), sorted(s)) for i, s in enumerate(sets)], "record_id string, user_id string, items array<string>")


def test_baselines(spark):
    recs = rec_frame(spark, ["ab", "ab", "a", "bcd", "ab"])
    v = lambda df: {r.metric: r.value for r in df.collect()}
    assert v(baselines.empty_all(recs)) == {"add": 0, "del": 10}
    assert v(baselines.fill_all(recs)) == {"add": 10, "del": 0}
    assert v(baselines.single_group(recs)) == {"add": 2, "del": 2}
    assert v(baselines.drop_rare(recs, 2)) == {"add": 0, "del": 4}
    for g in (baselines.sorted_chunks(recs.withColumn("b", F.lit("x")), 2, "b"), baselines.random_groups(recs, 2, buckets=1)):
        assert sorted(Counter(r.group_id for r in g.collect()).values()) == [2, 3]
    df = spark.createDataFrame([("x", "r1", "s"), ("y", "r1", "s"), ("z", "r2", "s"), ("x", "r1", "t")], "n string, r string, m string")
    got = {r.levels: (r.classes, r.suppressed) for r in baselines.generalize(df, [["n", "r"], ["m"]], 2).collect()}
    assert got["0,0"] == (4, 4) and got["1,0"] == (3, 2) and got["2,1"] == (1, 0) and len(got) == 6
    log = log_frame(spark, MINI)
    assert baselines.pseudonymize(log, "k").select("user_id").distinct().count() == 5


def test_precluster_alternatives(spark):
    recs = rec_frame(spark, ["abcde", "abcdf", "xyz", "xyw", "qrs"])
    near = {(r.a, r.b) for r in lsh.pairs_within(recs, 0.5).collect()}
    assert near == {("r0", "r1"), ("r2", "r3")}
    for b in (lsh.precluster_pairs(recs, 0.5), lsh.precluster_mllib(recs, 0.5, tables=40)):
        by = defaultdict(set)
        for r in b.collect():
            by[r.bucket_id].add(r.record_id)
        assert sorted(map(sorted, by.values())) == [["r0", "r1"], ["r2", "r3"], ["r4"]]
    assert lsh.precluster_bands(recs, 1, 6).count() == 5
    perm = lsh.minhash_permutation(recs, 3)
    assert perm.count() == 5
    big = rec_frame(spark, [["a", f"x{i}"] for i in range(37)]).withColumn("bucket_id", F.lit("b"))
    sizes = [r["count"] for r in lsh.refine(big, 10, 3).groupBy("bucket_id").count().collect()]
    assert sum(sizes) == 37 and min(sizes) >= 10
    kept, small = lsh.split_small(recs.withColumn("bucket_id", F.substring("record_id", 1, 1)), 3, "user")
    assert kept.count() == 5 and small.count() == 0


def test_measures(spark):
    recs = rec_frame(spark, ["ab", "ab", "ac", "d"], {0: "u", 1: "u"})
    a = measures.audit(recs, 2).first()
    assert (a.least, a.violations, a.sets) == (1, 2, 3)
    assert measures.audit(recs, 2, "user").first().violations == 4
    u = measures.uniqueness(recs, 2).first()
    assert (u.records, u.unique_records, u.below_k) == (4, 2, 2)
    five = rec_frame(spark, ["123", "12", "13", "456", "45"]).withColumn("bucket_id", F.lit("b"))
    assert measures.lower_bound(five, 2, "bucket_id").first().bound == 2.5
    assert measures.ratio_exact(five, 2).first().best == 3
    s = measures.cluster_stats(five.withColumn("bucket_id", F.element_at("items", 1))).first()
    assert (s.clusters, s.largest, s.top_item) == (2, 3, "1")
    pair = spark.createDataFrame([(list("abc"), list("bcd"))], "ia array<string>, ib array<string>")
    c = measures.collision_calibration(pair, 2, 150).first()
    assert c.expected == pytest.approx(0.25) and abs(c.observed - 0.25) < 0.16
    p = measures.itemset_pairs(recs, 2).collect()
    assert [(r.x, r.y, r.n) for r in p] == [("a", "b", 2)]


def test_attack(spark):
    recs = rec_frame(spark, ["abc", "abd", "xyz", "xyz"])
    r = attacks.attack_rate(recs, recs, known=3, of=3, exclude_top=0).first()
    assert (r.victims, r.unique_matches) == (4, 2)
    assert attacks.attack_rate(recs, recs, known=2, of=3, exclude_top=2).first().victims == 2
    s = attacks.stitch_risk(rec_frame(spark, ["ab", "ac", "bd"], {0: "u", 1: "u", 2: "v"})).first()
    assert (s.pairs, s.same_user) == (2, 1)


def test_utility(spark):
    recs = rec_frame(spark, ["ab", "ab", "abc", "c"])
    same = utility.itemset_utility(recs, recs, 0.5).first()
    assert same.precision == same.recall == 1
    assert utility.suggestion_utility(recs, recs).first().kept_share == 1
    less = rec_frame(spark, ["a", "a", "c", "c"])
    assert utility.itemset_utility(recs, less, 0.5).first().recall < 1
    labels = recs.select("record_id", F.array_contains("items", "a").cast("int").alias("label"))
    assert utility.label_utility(recs.unionByName(recs.withColumn("record_id", F.concat("record_id", F.lit("x")))), labels).count() == 1


def test_placement(spark):
    before = spark.createDataFrame([("a b",)], "query string")
    after = spark.createDataFrame([("a b", ["b"]), ("a z", ["z"])], "after string, inserted array<string>")
    r = measures.placement_loss(before, after).first()
    assert r.placed == 2 and r.loss == 0.5


@pytest.mark.parametrize("name", ["thread_stats", "stitch_risk", "anonymize_log_k3", "case_view"])
def test_registered_log_queries_take_either_similarity(spark, monkeypatch, name):
    seen = []

    class Enough(Exception):
        pass

    def stop(log, o=threads.ThreadOptions(), corpus=None):
        seen.append((o.similarity, corpus is not None))
        raise Enough

    monkeypatch.setattr(threads, "assign_threads", stop)
    with pytest.raises(Enough):
        QUERIES[name](spark, "/root/testdata/sf0.001")
    assert seen == [("any", True)]
