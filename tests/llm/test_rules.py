import re

from pyspark.sql import functions as F

from setanon.llm import rules

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(text):
    t = text or ""
    w = WORD.findall(t)
    lines = [x for x in t.split("\n") if WORD.search(x)]
    wins = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    hit = set()
    for i, x in enumerate(wins):
        if wins.count(x) > 1:
            hit.update(range(i, i + 5))
    return (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), sum(x in lines[:i] for i, x in enumerate(lines)), len(hit))


TEXTS = [
    None, "", " \t\n", "one", "a b c d e a b c d e x", "a a a a a a a a", "\x0bq\x0cw e r\n\nr\n r\n", "é à #|<> \U0001f600 x\n" * 4,
    "p q r s t u p q r s t v w x y z " * 3, "line\nline\nLine\n", "  lead and trail  ", "a b c d e f",
]


def test_counts_equal_brute_force(spark):
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(TEXTS)], "doc_id long, text string, n_words string")
    got = {r.doc_id: (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in rules.measured(df).collect()}
    assert got == {i: brute(t) for i, t in enumerate(TEXTS)}


def test_given_documents_equal_brute_force(spark):
    df = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    short = df.where(F.length("text") < 3000)
    text = {r.doc_id: r.text for r in short.collect()}
    for r in rules.measured(short).collect():
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute(text[r.doc_id])


def test_em_finds_the_noisy_rule():
    import random

    rnd, counts = random.Random(3), {}
    for _ in range(20000):
        good = rnd.random() < 0.85
        v = tuple((1 if good == (rnd.random() < a) else -1) if rnd.random() < 0.8 else 0 for a in (0.95, 0.9, 0.9, 0.85, 0.6, 0.9, 0.9))
        counts[v] = counts.get(v, 0) + 1
    acc = rules.estimate(sorted(counts.items()))
    assert abs(acc.right_on_good[0] - 0.95) < 0.03 and abs(acc.right_on_good[4] - 0.6) < 0.06
    assert acc.right_on_bad[0] > 0.8


def test_empty_and_repeats(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert rules.weak_quality(rules.measured(none)).count() == 0
    two = spark.createDataFrame([(1, "x " * 30), (1, "x " * 30), (None, None)], "doc_id long, text string")
    out = rules.weak_quality(rules.measured(two)).collect()
    assert len(out) == 3 and len({r.quality for r in out if r.doc_id == 1}) == 1


def test_plan_has_no_python(spark):
    df = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    plan = rules.measured(df)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan


def test_em_learns_a_mostly_bad_corpus():
    import random

    rnd, counts = random.Random(4), {}
    for _ in range(20000):
        good = rnd.random() < 0.25
        v = tuple((1 if good == (rnd.random() < 0.92) else -1) if rnd.random() < 0.9 else 0 for _ in range(7))
        counts[v] = counts.get(v, 0) + 1
    acc = rules.estimate(sorted(counts.items()))
    import math

    assert abs(1 / (1 + math.exp(-acc.prior)) - 0.25) < 0.03
    assert all(abs(a - 0.92) < 0.03 for a in acc.right_on_good + acc.right_on_bad)
