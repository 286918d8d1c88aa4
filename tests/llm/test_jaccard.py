import random

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from setanon.llm import jaccard as jx
from setanon.llm.common import components


def plain_sets(texts):
    out = []
    for t in texts:
        w = (t or "").encode().lower().split()
        out.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    return out


def plain_classes(ids, sets):
    root = list(range(len(sets)))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    least = {}
    for i, d in enumerate(ids):
        least[find(i)] = min(least.get(find(i), d), d)
    return {d: (len(sets[i]), least[find(i)]) for i, d in enumerate(ids)}


def texts_with_copies(seed, n=150):
    rnd = random.Random(seed)
    vocab = [f"w{i}" for i in range(4000)]
    line = " ".join(rnd.choices(vocab, k=12))
    out = []
    for _ in range(n):
        kind = rnd.random()
        if kind < 0.3 or len(out) < 10:
            t = rnd.choices(vocab, k=rnd.choice([0, 1, 3, 4, 5, 6, 20, 60, 120]))
        else:
            t = out[rnd.choice([0, 1, 2, rnd.randrange(len(out))])].split()
            for _ in range(rnd.choice([0, 0, 1, 1, 2, 3])):
                if t:
                    t[rnd.randrange(len(t))] = rnd.choice(vocab)
        out.append(" ".join(t))
    return [t + " " + line if rnd.random() < 0.4 else t.upper() if rnd.random() < 0.1 else t for t in out] + ["", " \t", line, line]


def test_query_equals_brute_force(spark):
    for seed, opt in ((1, jx.Options(frequent=4, short_posting=3)), (2, jx.Options(frequent=2, max_frequent=10, short_posting=2)), (3, jx.Options())):
        texts = texts_with_copies(seed)
        ids = random.Random(seed).sample(range(10_000), len(texts))
        df = spark.createDataFrame(list(zip(ids, ids, texts)), "row_key long, doc_id long, text string")
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in jx.classes(df, opt).collect()}
        assert got == plain_classes(ids, plain_sets(texts))


def test_large_near_copy_group(spark):
    for seed, base_in in ((7, True), (8, False)):
        rnd = random.Random(seed)
        vocab = [f"v{i}" for i in range(500)]
        base = rnd.choices(vocab, k=120)
        texts = [" ".join(base)] if base_in else []
        for i in range(140):
            t = list(base) if i % 4 else texts[rnd.randrange(len(texts))].split() if texts else list(base)
            for _ in range(rnd.randint(1, 6)):
                t[rnd.randrange(len(t))] = rnd.choice(vocab)
            texts.append(" ".join(t))
        texts += [" ".join(rnd.choices(vocab, k=40)) + " " + " ".join(base[:14]) for _ in range(40)]
        ids = list(range(len(texts)))
        df = spark.createDataFrame(list(zip(ids, ids, texts)), "row_key long, doc_id long, text string")
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in jx.classes(df).collect()}
        assert got == plain_classes(ids, plain_sets(texts))


def test_keep_one(spark):
    rows = [(3, "a b c d e f"), (3, "a b c d e f"), (None, "A b c d e f"), (9, None), (9, ""), (4, "other words are here now"), (5, "other words are here now")]
    df = spark.createDataFrame([(a, b, "n", 1) for a, b in rows], "doc_id long, text string, node string, n long")
    out = jx.keep_one(df)
    assert out.columns == df.columns
    assert sorted((r.text or "").lower() for r in out.collect()) == ["", "", "a b c d e f", "other words are here now"]
    assert jx.keep_one(df.limit(0)).count() == 0


@settings(max_examples=200, deadline=None)
@given(st.sets(st.integers(0, 60)), st.sets(st.integers(0, 60)))
def test_filters_lose_nothing(x, y):
    opt = jx.Options()
    a, b = (np.asarray(sorted(s), np.uint64) for s in (x, y))
    truth = bool(x and y) and 100 * len(x & y) >= 80 * len(x | y)
    if x and y:
        assert jx.linked(a, b, opt) == truth
        if truth:
            assert set(a[: jx.prefix_length(len(a), opt)].tolist()) & set(b[: jx.prefix_length(len(b), opt)].tolist())


def test_components(spark):
    rnd = random.Random(4)
    edges = [(i, i + 1) for i in range(300)] + [(1000 + i, 1000) for i in range(200)] + [(rnd.randrange(5000, 5200), rnd.randrange(5000, 5200)) for _ in range(150)]
    got = {r.id: r.component_id for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    root = {}

    def find(i):
        root.setdefault(i, i)
        while root[i] != i:
            i = root[i]
        return i

    for a, b in edges:
        if a != b:
            x, y = sorted((find(a), find(b)))
            root[y] = x
    assert got == {i: find(i) for i in root}
