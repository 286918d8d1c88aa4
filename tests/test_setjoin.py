import random
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from setanon.operators import lsh, setjoin

SCHEMA = "record_id string, user_id string, items array<string>"


def brute(sets, t):
    up = {i: i for i in sets}

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for a in sets:
        for b in sets:
            if a < b and sets[a] and len(sets[a] & sets[b]) >= (t - 1e-9) * len(sets[a] | sets[b]):
                x, y = sorted((top(a), top(b)))
                up[y] = x
    out = defaultdict(set)
    for i in sets:
        out[top(i)].add(i)
    return {k: frozenset(v) for k, v in out.items()}


def test_similar_sets_share_a_prefix():
    rng = np.random.default_rng(5)
    for t in (0.5, 0.6, 0.7, 0.9):
        for _ in range(1500):
            n = int(rng.integers(1, 40))
            x = np.unique(rng.integers(-(2**62), 2**62, n))
            y = np.unique(np.r_[x[rng.random(len(x)) < 0.9], rng.integers(-(2**62), 2**62, int(rng.integers(0, 5)))])
            if len(y) and len(np.intersect1d(x, y)) >= (t - 1e-9) * len(np.union1d(x, y)):
                assert len(np.intersect1d(setjoin.neighbours(np.sort(x.view(np.uint64)).view(np.int64), t), setjoin.neighbours(np.sort(y.view(np.uint64)).view(np.int64), t)))


def test_sketches_bound_the_difference():
    rng = np.random.default_rng(7)
    for _ in range(400):
        x = np.unique(rng.integers(-(2**62), 2**62, int(rng.integers(1, 900))))
        y = np.unique(np.r_[x[rng.random(len(x)) < rng.random()], rng.integers(-(2**62), 2**62, int(rng.integers(1, 900)))])
        assert setjoin.differ_at_least(setjoin.sketch(x), setjoin.sketch(y)) <= len(np.setxor1d(x, y))


@pytest.mark.parametrize("t", [0.6, 0.7, 0.9])
def test_classes_equal_brute_force(spark, t):
    """Copies, near copies in a group above one posting's limit, short sets and empty ones."""
    rng = random.Random(int(t * 10))
    sets = {}
    for i in range(220):
        kind = i % 4
        if kind == 0:  # changes of one set, some far from others
            s = {f"w{j}" for j in range(40)} - {f"w{rng.randrange(40)}" for _ in range(rng.randint(0, 9))} | {f"x{rng.randrange(90)}" for _ in range(rng.randint(0, 6))}
        elif kind == 1:
            s = {rng.choice("abcdefgh") for _ in range(rng.randint(0, 7))}
        elif kind == 2:
            s = {f"y{(i // 40) * 100 + j}" for j in range(20)} - {f"y{(i // 40) * 100 + rng.randrange(20)}"}
        else:
            s = {f"z{rng.randrange(400)}" for _ in range(rng.randint(1, 30))}
        sets[f"{i:03d}"] = s
    recs = spark.createDataFrame([(i, "u", sorted(s)) for i, s in sets.items()], SCHEMA)
    got = defaultdict(set)
    for r in lsh.precluster_pairs(recs, t).collect():
        got[r.bucket_id].add(r.record_id)
    assert {k: frozenset(v) for k, v in got.items()} == brute(sets, t)


def test_unlike_sets_of_frequent_items_make_no_pairs(spark):
    """1,500 sets of 40 out of 300 items: each item is in 200 of them, and single items would pair nearly all."""
    rng = random.Random(1)
    recs = spark.createDataFrame([(f"{i}", "u", sorted({f"v{rng.randrange(300)}" for _ in range(40)})) for i in range(1500)], SCHEMA)
    pairs = setjoin.met(setjoin.named_sets(recs), 0.7).where("a <> b").select(F.least("a", "b"), F.greatest("a", "b")).distinct().count()
    assert pairs < 1500 * 1499 // 2 // 5
