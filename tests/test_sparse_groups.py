"""Groups of large sets: compared through their items, without a matrix of all words of a bucket."""

import random

import numpy as np
import pytest

from setanon.operators import kernel


def plain_groups(m, k):
    """Every seed is priced anew for each group."""
    n, free, out = len(m), list(range(len(m))), []
    if n < 2 * k:
        return [free]
    d = kernel.distances(m)
    while len(free) >= 2 * k:
        priced = []
        for s in free:
            near = sorted(free, key=lambda u: (d[s, u], u))[: min(2 * k - 1, len(free) - k)]
            for j in range(k, len(near) + 1):
                priced.append((kernel.stars(m[near[:j]]) / j, -j, sorted(near[:j])))
        group = min(priced)[2]
        out.append(group)
        free = [u for u in free if u not in group]
    return out + [free] if free else out


@pytest.mark.parametrize("seed", range(12))
def test_balls_of_sets_equal_plain_greedy(seed):
    rnd = random.Random(seed)
    n, k, words = rnd.choice([7, 20, 45]), rnd.choice([1, 2, 3, 4]), rnd.choice([5, 12, 200])
    sets = [frozenset(f"w{int(rnd.paretovariate(0.7)) % words}" for _ in range(rnd.randint(0, 25))) for _ in range(n)]
    m = kernel.Bucket([f"{i:03d}" for i in range(n)], ["u"] * n, sets).m
    assert (kernel.set_distances(sets) == kernel.distances(m)).all()
    assert kernel.ball_groups(sets, k) == kernel.ball_groups(m, k) == plain_groups(m, k)


def test_large_vocabulary_needs_no_matrix():
    rnd = np.random.default_rng(1)
    n = 400
    sets = [frozenset(f"w{x}" for x in rnd.zipf(1.3, 150) % 100_000) for _ in range(n)]
    b = kernel.Bucket([f"{i:04d}" for i in range(n)], ["u"] * n, sets)
    opt = kernel.SolveOptions(2, improve=False)
    groups = kernel.grouped(b, opt)
    told = [kernel.target(b, g, opt) for g in groups]
    assert "m" not in vars(b) and "items" not in vars(b)
    assert sorted(i for g in groups for i in g) == list(range(n)) and min(map(len, groups)) >= 2
    for g, t in zip(groups[:50], told):
        assert t == sorted(x for x in set().union(*(sets[i] for i in g)) if 2 * sum(x in sets[i] for i in g) > len(g))
