"""The kernels' shortcuts give what their definitions give, and pay off on large buckets."""

import random
import time

import numpy as np

from setanon.operators import kernel


def local_search(d, price):
    """Adding, dropping and swapping by whole totals, the first best move of each step."""
    n = len(d)
    total = lambda o: sum(price[x] for x in o) + sum(min(d[p][x] for x in o) for p in range(n))
    opened = [min(range(n), key=lambda j: total([j]))]
    while True:
        out = [j for j in range(n) if j not in opened]
        moves = [[*opened, j] for j in out] + ([opened[:x] + opened[x + 1 :] for x in range(len(opened))] if len(opened) > 1 else [])
        moves += [[*opened[:x], *opened[x + 1 :], j] for x in range(len(opened)) for j in out]
        best = min(moves, key=total, default=opened)
        if total(best) >= total(opened):
            return np.asarray([min(sorted(opened), key=lambda x: (d[p][x], x)) for p in range(n)])
        opened = best


def sets_of(n, items, seed):
    rnd = random.Random(seed)
    return [frozenset(rnd.sample(range(items), rnd.randrange(1, 6))) for _ in range(n)]


def test_local_search_is_that_of_whole_totals():
    for seed in range(6):
        d = kernel.distances(kernel.matrix(sets_of(14, 9, seed), list(range(9))))
        price = kernel.opening_price(d, 4, 0.5)
        assert kernel.facility_local_search(d, price).tolist() == local_search(d, price).tolist()


def test_local_search_counts_only_points_that_moved():
    """Each step used to count all points against all others: 8 seconds for such a bucket, now half a second."""
    d = kernel.distances(kernel.matrix(sets_of(2000, 60, 1), list(range(60))))
    began = time.process_time()
    serve = kernel.facility_local_search(d, kernel.opening_price(d, 6, 0.5))
    assert time.process_time() - began < 4 and (serve >= 0).all()


def test_balls_of_large_k_stop_where_the_price_rises():
    ball = kernel._Ball([frozenset(s) for s in ("ab", "ab", "abc", "abc", "abcd", "xyz")], 2)
    seen = []
    ball.bits = [Seen(x, i, seen) for i, x in enumerate(ball.bits)]
    assert ball.best([0, 1, 2, 3, 4, 5]) == (0.0, -2, (0, 1)) and 3 not in seen


class Seen(int):
    """A number that tells when it is joined."""

    def __new__(cls, value, i, seen):
        out = super().__new__(cls, value)
        out.i, out.seen = i, seen
        return out

    def __ror__(self, other):
        self.seen.append(self.i)
        return int(self) | int(other)
