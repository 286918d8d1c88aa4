"""Bucket-local solvers in numpy. A bucket's records are units (a record, or all records of one
user), folded to a 0/1 matrix over the bucket's own items. Every tie breaks by record id."""

from __future__ import annotations

import heapq
import itertools
from collections import Counter
from dataclasses import dataclass
from functools import cached_property

import numpy as np


@dataclass
class Bucket:
    """Records of one bucket, sorted by id. The dense matrix is made only for solvers that read it."""

    ids: list[str]
    users: list[str]
    sets: list[frozenset]

    def __post_init__(self):
        order = sorted(range(len(self.ids)), key=lambda i: self.ids[i])
        self.ids, self.users, self.sets = ([x[i] for i in order] for x in (self.ids, self.users, self.sets))

    @cached_property
    def items(self) -> list[str]:
        return sorted(set().union(*self.sets))

    @cached_property
    def m(self) -> np.ndarray:
        """Record x item."""
        return matrix(self.sets, self.items)

    def units(self, unit: str) -> list[list[int]]:
        """Record numbers of each unit; with users, one user's records stay together."""
        if unit == "record":
            return [[i] for i in range(len(self.ids))]
        by: dict[str, list[int]] = {}
        for i, u in enumerate(self.users):
            by.setdefault(u, []).append(i)
        return list(by.values())


def matrix(sets: list, items: list) -> np.ndarray:
    code = {x: i for i, x in enumerate(items)}
    m = np.zeros((len(sets), len(items)), np.float32)
    for i, s in enumerate(sets):
        m[i, [code[x] for x in s]] = 1
    return m


def distances(m: np.ndarray) -> np.ndarray:
    """Pairwise Hamming distances from intersections; bit vectors exist only inside a bucket."""
    size = m.sum(axis=1)
    return (size[:, None] + size[None, :] - 2 * (m @ m.T)).astype(np.int32)


def flips(count: np.ndarray, g) -> np.ndarray:
    return np.minimum(count, g - count).sum(axis=-1)


def stars(rows: np.ndarray) -> int:
    c = rows.sum(axis=0)
    return int(len(rows) * ((c > 0) & (c < len(rows))).sum())


# ---- suppression: greedy cover ---------------------------------------------------------------


#: Pairs of records that are counted at once, when sets are compared through their items.
PAIRS = 1 << 21


def set_distances(sets: list) -> np.ndarray:
    """``distances`` of sets. Items that many sets hold are columns of a small matrix; each other
    item adds one to the pairs of its holders, and one that a single set holds adds to no pair."""
    n, size = len(sets), np.asarray([len(s) for s in sets], np.int64)
    code: dict = {}
    item = np.fromiter((code.setdefault(x, len(code)) for s in sets for x in s), np.int64, int(size.sum()))
    row = np.repeat(np.arange(n), size)[np.argsort(item, kind="stable")]
    held = np.bincount(item, minlength=len(code))
    start = np.cumsum(held) - held
    many = np.flatnonzero(held > max(8, n // 16))
    both = np.zeros((n, n), np.float32)
    for a in range(0, len(many), 1024):
        part = np.zeros((n, len(many[a : a + 1024])), np.float32)
        for j, i in enumerate(many[a : a + 1024].tolist()):
            part[row[start[i] : start[i] + held[i]], j] = 1
        both += part @ part.T
    both, flat, waiting = both.astype(np.int32).ravel(), [], 0

    def add():
        nonlocal flat, waiting
        if flat:
            both[:] += np.bincount(np.concatenate(flat), minlength=n * n).astype(np.int32)
        flat, waiting = [], 0

    for h in range(2, max(8, n // 16) + 1):
        of = start[held == h]
        step = max(1, PAIRS // (h * h))
        for a in range(0, len(of), step):
            rows = row[of[a : a + step, None] + np.arange(h)]
            flat.append((rows[:, :, None] * n + rows[:, None, :]).ravel())
            waiting += len(flat[-1])
            if waiting >= PAIRS:
                add()
    add()
    both = both.reshape(n, n)
    np.fill_diagonal(both, size)
    return (size[:, None] + size[None, :] - 2 * both).astype(np.int32)


class _Ball:
    """Best prefix of a seed's nearest free units: price is stars per record."""

    def __init__(self, sets: list, k: int):
        code: dict = {}
        for s in sets:
            for x in s:
                code.setdefault(x, len(code))
        self.bits = [sum(1 << code[x] for x in s) for s in sets]  # unions and intersections are steps of the machine
        self.k, self.d = k, set_distances(sets)
        self.free = np.ones(len(sets), bool)
        self.ahead = [np.zeros(0, np.int64) for _ in sets]  # a seed's nearest units, as far as they were put in order

    def nearest(self, seed: int, most: int) -> list[int]:
        """The nearest free units in order, ties by number. Some more are kept for later, since
        the next ones in a list are still the nearest when units before them are taken."""
        free = self.free
        near = self.ahead[seed]
        near = near[free[near]]
        if len(near) < most:
            left = np.flatnonzero(free)
            key = self.d[seed, left].astype(np.int64) * len(free) + left
            some = 4 * most + 16
            if some < len(key):
                key = np.partition(key, some)[:some]
            key.sort()
            near = key % len(free)
        self.ahead[seed] = near
        return near[:most].tolist()

    def best(self, near: list[int]) -> tuple[float, int, tuple[int, ...]]:
        """A price never falls as a ball grows, so the longest of the cheapest ends where it rises."""
        bits, least = self.bits, max(self.k, 2)
        union = common = bits[near[0]]
        price, size = float("inf"), 0
        for j, u in enumerate(near[1:], 2):
            s = bits[u]
            union, common = union | s, common & s
            if j >= least:
                now = (union ^ common).bit_count()
                if now > price:
                    break
                price, size = now, j
        if self.k == 1 and price > 0:
            price, size = 0, 1
        return float(price), -size, tuple(sorted(near[:size]))


def ball_groups(m: np.ndarray | list, k: int) -> list[list[int]]:
    """Disjoint groups of k to 2k-1: the cheapest ball over all seeds is committed, again and again.
    Units are rows of a 0/1 matrix or sets.

    A ball costs at least the distance of its k-th unit, which only rises while units are taken. So a
    seed whose nearest units were taken waits with that bound, and is priced when the bound comes first."""
    n = len(m)
    if n < 2 * k:
        return [list(range(n))]
    ball, left, out = _Ball([frozenset(np.flatnonzero(r).tolist()) for r in m] if isinstance(m, np.ndarray) else m, k), n, []
    free, most = ball.free, min(2 * k - 1, n - k)
    least = np.partition(ball.d, k - 1, axis=1)[:, k - 1].astype(float)  # by bound
    price, priced = least.copy(), np.zeros(n, bool)
    reach = np.zeros((n, most), np.int64)  # of the seeds that are priced
    best: list[tuple] = [()] * n
    while True:
        low = price[free].min()
        first = np.flatnonzero(free & (price == low))
        wait = first[~priced[first]].tolist()
        for s in wait:
            near = ball.nearest(s, most)
            least[s] = price[s] = ball.d[s, near[k - 1]]
            if price[s] <= low:
                best[s], priced[s], reach[s, :most] = ball.best(near), True, near
                price[s] = best[s][0]
        if wait:
            continue
        group = list(min(best[s] for s in first.tolist())[2])
        out.append(group)
        free[group] = False
        left -= len(group)
        if left < 2 * k:
            break
        now = min(2 * k - 1, left - k)
        late = priced & ~free[reach[:, :most]].all(axis=1) if now == most else priced
        price[late], priced[late], most = least[late], False, now
    if left:
        out.append(np.flatnonzero(free).tolist())
    return out


def candidate_groups(m: np.ndarray, k: int, kind: str) -> list[tuple[int, ...]]:
    """Groups that a cover may choose from: every subset of k to 2k-1, or all balls' prefixes."""
    n, most = len(m), min(2 * k - 1, len(m))
    if kind == "exhaustive":
        return [g for size in range(k, most + 1) for g in itertools.combinations(range(n), size)]
    d, out = distances(m), set()
    for s in range(n):
        near = np.lexsort((np.arange(n), d[s]))[:most]
        out.update(tuple(sorted(near[:j].tolist())) for j in range(k, most + 1))
    return sorted(out)


def cover(m: np.ndarray, k: int, groups: list[tuple[int, ...]]) -> list[tuple[int, ...]]:
    """Greedy set cover with overlap: least stars for each newly covered unit. A group's price only
    rises as units are covered, so it is priced anew only when it comes first."""
    cost = [stars(m[list(g)]) for g in groups]
    heap = [(c / len(g), -len(g), g, c) for c, g in zip(cost, groups)]
    heapq.heapify(heap)
    left, out = set(range(len(m))), []
    while left:
        price, size, g, c = heapq.heappop(heap)
        new = len(left.intersection(g))
        if not new:
            continue
        if c / new > price:
            heapq.heappush(heap, (c / new, size, g, c))
            continue
        out.append(g)
        left -= set(g)
    return out


def cover_to_partition(groups: list[tuple[int, ...]], k: int, m: np.ndarray | None = None) -> list[list[int]]:
    """Disjoint groups from overlapping ones: a shared unit leaves a group that has more than k,
    else the two merge; groups of 2k or more are split."""
    parts = {i: set(g) for i, g in enumerate(groups)}
    held: dict[int, set[int]] = {}
    for i, g in parts.items():
        for u in g:
            held.setdefault(u, set()).add(i)
    for u in sorted(held):
        while len(held[u]) > 1:
            j, i = sorted(held[u])[:2]
            if len(parts[i]) > k or len(parts[j]) > k:
                shut = i if len(parts[i]) > k else j
                parts[shut].discard(u)
                held[u].discard(shut)
                continue
            for v in parts[i]:
                held[v].discard(i)
                held[v].add(j)
            parts[j] |= parts.pop(i)
    out = []
    for p in (sorted(p) for p in parts.values()):
        while len(p) >= 2 * k:
            if m is not None:  # a unit and its nearest k-1 stay together
                d = distances(m[p])
                seed = int(d.sum(axis=1).argmax())
                near = sorted(range(len(p)), key=lambda x: (d[seed, x], x))[:k]
                out.append(sorted(p[x] for x in near))
                p = [u for x, u in enumerate(p) if x not in near]
            else:
                out.append(p[:k])
                p = p[k:]
        out.append(p)
    return sorted(out)


def greedy_disjoint(m: np.ndarray, k: int, groups: list[tuple[int, ...]]) -> list[list[int]]:
    """The exhaustive greedy without overlap: what stays must still form a group."""
    left, out = set(range(len(m))), []
    priced = sorted((stars(m[list(g)]) / len(g), -len(g), g) for g in groups)
    for _, _, g in priced:
        if len(left) < 2 * k:
            break
        if left.issuperset(g) and len(left) - len(g) >= k:
            out.append(list(g))
            left -= set(g)
    return out + [sorted(left)] if left else out


def popular(bucket: Bucket, units: list[list[int]], k: int) -> list[list[int]]:
    """Units of single equal sets that at least k units hold: groups that cost nothing."""
    by: dict[frozenset, list[int]] = {}
    for u, recs in enumerate(units):
        if len({bucket.sets[i] for i in recs}) == 1:
            by.setdefault(bucket.sets[recs[0]], []).append(u)
    return [g for g in by.values() if len(g) >= k]


def nearest_group(bucket: Bucket, units: list[list[int]], groups: list[list[int]], unit: int) -> int:
    """The group whose flips rise least when a unit joins it. Items that neither holds cost nothing."""
    own, w, rise = Counter(x for i in units[unit] for x in bucket.sets[i]), len(units[unit]), []
    for group in groups:
        recs = [i for u in group for i in units[u]]
        held, g = Counter(x for i in recs for x in bucket.sets[i]), len(recs)
        rise.append(sum(min(held[x] + own[x], g + w - held[x] - own[x]) - min(held[x], g - held[x]) for x in held.keys() | own.keys()))
    return rise.index(min(rise))


def improved(m: np.ndarray, w: np.ndarray, groups: list[list[int]], k: int, passes: int) -> list[list[int]]:
    """Moves single units out of groups above k while the total of flips falls. ``m`` holds item
    counts of units, ``w`` their record counts."""
    groups = [list(g) for g in groups]
    count, size = np.stack([m[g].sum(axis=0) for g in groups]), np.asarray([w[g].sum() for g in groups])
    for _ in range(passes):
        moved = False
        for a in range(len(groups)):
            for u in sorted(groups[a]):
                if len(groups[a]) <= k:
                    break
                gain = flips(count[a], size[a]) - flips(count[a] - m[u], size[a] - w[u])
                more = flips(count + m[u], (size + w[u])[:, None]) - flips(count, size[:, None])
                more[a] = np.inf
                b = int(np.argmin(more))
                if more[b] < gain:
                    groups[a].remove(u)
                    groups[b].append(u)
                    count[a] -= m[u]
                    size[a] -= w[u]
                    count[b] += m[u]
                    size[b] += w[u]
                    moved = True
        if not moved:
            break
    return groups


# ---- exact -----------------------------------------------------------------------------------


def group_cost(rows: np.ndarray, objective: str) -> float:
    """Cost of one group: flip, star, medoid (own member as centre), add only or delete only."""
    c, g = rows.sum(axis=0), len(rows)
    if objective == "flip":
        return float(np.minimum(c, g - c).sum())
    if objective == "star":
        return float(stars(rows))
    if objective == "medoid":
        return float(distances(rows).sum(axis=1).min())
    if objective == "add":
        return float(((c > 0) * (g - c)).sum())
    if objective == "del":
        return float(((c < g) * c).sum())
    raise ValueError(f"unknown objective {objective}")


def exact_groups(m: np.ndarray, k: int, objective: str = "flip", max_n: int = 14, most: int | None = None) -> tuple[float, list[list[int]]]:
    """The optimal grouping: the first free record is grouped with every choice of companions,
    memoised on what is left."""
    n = len(m)
    if n > max_n:
        raise ValueError(f"{n} records: exact search stops at {max_n}")
    if n < k:
        raise ValueError(f"{n} records cannot form a group of {k}")
    most = most or 2 * k - 1
    memo: dict[int, tuple[float, tuple]] = {0: (0.0, ())}
    cost: dict[tuple, float] = {}

    def solve(left: int) -> tuple[float, tuple]:
        if left in memo:
            return memo[left]
        free = [i for i in range(n) if left >> i & 1]
        best = (float("inf"), ())
        for size in range(k, min(most, len(free)) + 1):
            if 0 < len(free) - size < k:
                continue
            for rest in itertools.combinations(free[1:], size - 1):
                g = (free[0], *rest)
                if g not in cost:
                    cost[g] = group_cost(m[list(g)], objective)
                if cost[g] >= best[0]:
                    continue
                sub, groups = solve(left & ~sum(1 << i for i in g))
                if cost[g] + sub < best[0]:
                    best = (cost[g] + sub, (g, *groups))
        memo[left] = best
        return best

    total, groups = solve((1 << n) - 1)
    return total, [list(g) for g in groups]


def exact_assignment(m: np.ndarray, k: int, max_n: int = 14) -> tuple[float, list[list[int]], list[int]]:
    """Optimum of the integer program with data points as centres: every point is assigned once,
    and an open centre, which need not serve itself, serves at least k points."""
    total, groups = _centred(m, k, max_n)
    d = distances(m)
    return total, groups, [int(d[g].sum(axis=0).argmin()) for g in groups]


def _centred(m: np.ndarray, k: int, max_n: int):
    n = len(m)
    if not k <= n <= max_n:
        raise ValueError(f"needs {k} to {max_n} records")
    d = distances(m)
    memo: dict[int, tuple[float, tuple]] = {0: (0.0, ())}

    def solve(left: int):
        if left in memo:
            return memo[left]
        free = [i for i in range(n) if left >> i & 1]
        best = (float("inf"), ())
        for size in range(k, min(2 * k - 1, len(free)) + 1):
            if 0 < len(free) - size < k:
                continue
            for rest in itertools.combinations(free[1:], size - 1):
                g = (free[0], *rest)
                own = float(d[list(g)].sum(axis=0).min())
                if own < best[0]:
                    sub, groups = solve(left & ~sum(1 << i for i in g))
                    if own + sub < best[0]:
                        best = (own + sub, (g, *groups))
        memo[left] = best
        return best

    total, groups = solve((1 << n) - 1)
    return total, [list(g) for g in groups]


# ---- clustering: facilities with a minimum load ----------------------------------------------


def opening_price(d: np.ndarray, k: int, alpha: float) -> np.ndarray:
    """Price of opening each point: its k nearest points' distances, itself included, scaled."""
    return 2 * alpha / (1 - alpha) * np.sort(d, axis=1)[:, :k].sum(axis=1)


def facility_greedy(d: np.ndarray, price: np.ndarray) -> np.ndarray:
    """Each point's facility: the facility with its nearest free points of least mean cost opens
    first; one that is open costs nothing more. A facility's mean only rises while points are taken,
    so it is computed anew only when it comes first."""
    n, price = len(d), price.astype(float).copy()
    order, serve, free = np.argsort(d, axis=1, kind="stable"), np.full(n, -1), np.ones(n, bool)

    def best(j: int) -> tuple[float, int]:
        mine = order[j][free[order[j]]]
        mean = (price[j] + np.cumsum(d[j, mine])) / np.arange(1, len(mine) + 1)
        i = int(mean.argmin())
        return float(mean[i]), i + 1

    heap = [(best(j)[0], j) for j in range(n)]
    heapq.heapify(heap)
    while free.any():
        _, j = heapq.heappop(heap)
        now, size = best(j)
        if heap and (now, j) > heap[0]:
            heapq.heappush(heap, (now, j))
            continue
        mine = order[j][free[order[j]]][:size]
        serve[mine], free[mine], price[j] = j, False, 0
        if free.any():
            heapq.heappush(heap, (best(j)[0], j))
    opened = np.unique(serve)  # a point goes to the nearest open facility
    return opened[d[:, opened].argmin(axis=1)]


def facility_local_search(d: np.ndarray, price: np.ndarray) -> np.ndarray:
    """Facilities by adding, dropping and swapping while the total falls. All moves of a step are
    priced together from each point's nearest and second nearest open facility."""
    n, at = len(d), np.arange(len(d))
    d = d.astype(float)
    opened = [int((price + d.sum(axis=0)).argmin())]
    less = np.zeros(n)  # what each point as a facility takes off its nearer points
    extra = np.zeros((n, n))  # by facility: what the points that lose it cost more, where a point opens instead
    own, first, second = np.full(n, -1), np.full(n, np.inf), np.full(n, np.inf)

    def moved(sign: int, rows: np.ndarray) -> None:
        """Counts some points in or out, with their facility and distances as they are now."""
        for a in range(0, len(rows), 256):
            part = rows[a : a + 256]
            part = part[np.argsort(own[part], kind="stable")]
            near = np.minimum(d[part], first[part][:, None])
            less[:] += sign * (near - first[part][:, None]).sum(axis=0)
            edge = np.flatnonzero(np.r_[True, own[part][1:] != own[part][:-1]])
            extra[own[part][edge]] += sign * np.add.reduceat(np.minimum(d[part], second[part][:, None]) - near, edge, axis=0)

    while True:
        o = np.asarray(opened)
        to = d[:, o]
        new = o[to.argmin(axis=1)]
        new_first = d[at, new]
        new_second = np.partition(to, 1, axis=1)[:, 1] if len(o) > 1 else np.full(n, np.inf)
        rows = np.flatnonzero((new != own) | (new_first != first) | (new_second != second))
        moved(-1, rows[own[rows] >= 0])  # distances are whole numbers, so sums stay exact
        own[rows], first[rows], second[rows] = new[rows], new_first[rows], new_second[rows]
        moved(1, rows)
        shut = np.isin(at, o)
        add = np.where(shut, np.inf, price + less)
        moves = [(float(add.min()), [*opened, int(add.argmin())])] if not shut.all() else []
        if len(o) > 1:
            drop = np.bincount(own, second - first, n)[o] - price[o]
            x = int(drop.argmin())
            moves.append((float(drop[x]), opened[:x] + opened[x + 1 :]))
        if not shut.all():
            # a point that loses its facility goes to its second nearest, or to the new one
            swap = extra[o] + add[None, :] - price[o][:, None]
            x, j = divmod(int(swap.argmin()), n)
            moves.append((float(swap[x, j]), [*opened[:x], *opened[x + 1 :], j]))
        gain, best = min(moves, key=lambda v: v[0], default=(0.0, opened))
        if gain >= -1e-9:
            break
        opened = best
    o = np.asarray(sorted(opened))
    return o[d[:, o].argmin(axis=1)]


def merge_underloaded(d: np.ndarray, serve: np.ndarray, bound: float) -> np.ndarray:
    """Closes the least loaded facility under the bound until none is left; its points go to the
    nearest open one."""
    serve = serve.copy()
    while True:
        opened, load = np.unique(serve, return_counts=True)
        low = load < bound
        if not low.any() or len(opened) == 1:
            return serve
        shut = opened[np.lexsort((opened, load))[0]]
        rest = opened[opened != shut]
        mine = np.flatnonzero(serve == shut)
        serve[mine] = rest[d[np.ix_(mine, rest)].argmin(axis=1)]


def split_big(m: np.ndarray, group: list[int], k: int) -> list[list[int]]:
    """A group of 2k or more, solved again inside."""
    if len(group) < 2 * k:
        return [group]
    return [[group[i] for i in g] for g in ball_groups(m[group], k)]


@dataclass(frozen=True)
class FacilityOptions:
    alpha: float = 0.5
    load: str = "strict"  # strict, relaxed (alpha times k only), or inflate (solved for k / alpha)
    solver: str = "greedy"  # or local
    split: bool = True


def facility_groups(m: np.ndarray, k: int, opt: FacilityOptions = FacilityOptions()) -> tuple[list[list[int]], list[int]]:
    """Groups and their data-point centres."""
    d = distances(m)
    kk = -(-k // opt.alpha) if opt.load == "inflate" else k
    kk = min(int(kk), len(m))
    price = opening_price(d, kk, opt.alpha)
    serve = facility_greedy(d, price) if opt.solver == "greedy" else facility_local_search(d, price)
    serve = merge_underloaded(d, serve, {"strict": k, "relaxed": opt.alpha * k, "inflate": opt.alpha * kk}[opt.load])
    groups = [np.flatnonzero(serve == j).tolist() for j in np.unique(serve)]
    if opt.split:
        groups = [g for x in groups for g in split_big(m, x, k)]
    return groups, [int(g[int(d[np.ix_(g, g)].sum(axis=1).argmin())]) for g in groups]


# ---- one entry for buckets -------------------------------------------------------------------


@dataclass(frozen=True)
class SolveOptions:
    k: int
    solver: str = "suppress"  # suppress, facility, exact, chunks, random
    candidates: str = "ball"  # ball, exhaustive, itemset
    overlap: bool = False
    popular_first: bool = True
    improve: bool = True
    max_passes: int = 3
    ops: str = "both"
    tie: str = "delete"
    unit: str = "record"
    weights: tuple[float, float] = (1.0, 1.0)
    recenter: str = "majority"
    max_n: int = 14
    facility: FacilityOptions = FacilityOptions()
    on_empty: str = "publish"  # publish, drop, keep_mode_item


def itemset_groups(m: np.ndarray, k: int) -> list[tuple[int, ...]]:
    """Candidate groups from frequent itemsets: for each closed set of items with support of k or
    more, the supporters nearest in size to it, k to 2k-1 of them."""
    seen, out, todo = set(), set(), [tuple()]
    while todo:
        base = todo.pop()
        have = m[:, list(base)].all(axis=1) if base else np.ones(len(m), bool)
        rows = np.flatnonzero(have)
        if len(rows) < k:
            continue
        closed = tuple(np.flatnonzero(m[rows].all(axis=0)).tolist())
        if closed in seen:
            continue
        seen.add(closed)
        near = rows[np.lexsort((rows, m[rows].sum(axis=1)))]
        for j in range(k, min(2 * k - 1, len(near)) + 1):
            out.add(tuple(sorted(near[:j].tolist())))
        last = max(base, default=-1)
        todo += [tuple(sorted({*closed, i})) for i in range(last + 1, m.shape[1]) if i not in closed and m[rows, i].sum() >= k]
    return sorted(out)


def grouped(bucket: Bucket, opt: SolveOptions) -> list[list[int]]:
    """Groups of record numbers, each of at least k units."""
    units, k = bucket.units(opt.unit), opt.k
    if len(units) < k:
        return []
    sparse = opt.solver == "suppress" and opt.candidates == "ball" and not opt.overlap and not opt.improve
    if not sparse:
        counts = np.stack([bucket.m[u].sum(axis=0) for u in units])
        weight = np.asarray([len(u) for u in units], np.float32)
        solid = (counts > 0).astype(np.float32)
    groups: list[list[int]] = []
    rest = list(range(len(units)))
    if opt.popular_first and opt.solver in ("suppress", "exact"):
        groups = popular(bucket, units, k)
        taken = {u for g in groups for u in g}
        rest = [u for u in rest if u not in taken]
        if 0 < len(rest) < k:  # too few to stand alone: they join the cheapest group
            for u in rest:
                groups[nearest_group(bucket, units, groups, u)].append(u)
            rest = []
    if rest:
        m = [frozenset().union(*(bucket.sets[i] for i in units[u])) for u in rest] if sparse else solid[rest]
        if opt.solver == "suppress":
            if opt.candidates == "ball" and not opt.overlap:
                part = ball_groups(m, k)
            else:
                kind = opt.candidates
                if kind == "exhaustive" and len(rest) > opt.max_n:
                    raise ValueError(f"{len(rest)} units: exhaustive candidates stop at {opt.max_n}; use ball or itemset, or smaller buckets")
                cands = itemset_groups(m, k) if kind == "itemset" else candidate_groups(m, k, kind)
                if opt.overlap:
                    cands += [g for g in candidate_groups(m, k, "ball") if kind == "itemset"]
                    part = cover_to_partition(cover(m, k, cands), k, m)
                else:
                    part = greedy_disjoint(m, k, cands)
                    part = [g for x in part for g in (split_big(m, x, k) if len(x) >= 2 * k else [x])]
        elif opt.solver == "facility":
            part = facility_groups(m, k, opt.facility)[0]
        elif opt.solver == "exact":
            part = exact_groups(m, k, {"both": "flip"}.get(opt.ops, opt.ops), opt.max_n)[1]
        elif opt.solver in ("chunks", "random"):
            if opt.solver == "chunks":
                order = sorted(range(len(rest)), key=lambda i: (sorted(bucket.sets[units[rest[i]][0]]), bucket.ids[units[rest[i]][0]]))
            else:
                import zlib

                order = sorted(range(len(rest)), key=lambda i: (zlib.crc32(bucket.ids[units[rest[i]][0]].encode()), bucket.ids[units[rest[i]][0]]))
            n = max(1, len(order) // k)
            part = [order[j * k : (j + 1) * k if j < n - 1 else len(order)] for j in range(n)]
        else:
            raise ValueError(f"unknown solver {opt.solver}")
        groups += [[rest[i] for i in g] for g in part]
    if opt.improve and opt.solver == "suppress" and len(groups) > 1 and opt.ops == "both":
        groups = improved(counts, weight, groups, k, opt.max_passes)
    return [sorted(i for u in g for i in units[u]) for g in groups]


def target(bucket: Bucket, group: list[int], opt: SolveOptions) -> list[str]:
    """The common set of a group."""
    add, drop = opt.weights
    sets = [bucket.sets[i] for i in group]
    all_items = add <= 0 or opt.on_empty == "keep_mode_item"  # then an item of no member may be kept
    items = bucket.items if all_items else sorted(set().union(*sets))
    rows = matrix(sets, items)
    c, g = rows.sum(axis=0), len(group)
    if opt.solver == "facility" and opt.recenter == "medoid":
        keep = rows[int(distances(rows).sum(axis=1).argmin())] > 0
    elif opt.ops == "add":
        keep = c > 0
    elif opt.ops == "del":
        keep = c == g
    else:
        keep = add * (g - c) <= drop * c if opt.tie == "insert" else add * (g - c) < drop * c
    if not keep.any() and opt.on_empty == "keep_mode_item":
        keep[int(c.argmax())] = True
    return [x for x, k in zip(items, keep) if k]


def solve(ids: list[str], users: list[str], sets: list[list[str]], opt: SolveOptions) -> list[tuple[str, str, list[str]]]:
    """(record id, least record id of its group, common set); empty when there are too few."""
    b = Bucket(list(ids), list(users), [frozenset(s) for s in sets])
    return [(b.ids[i], b.ids[min(g)], t) for g in grouped(b, opt) for t in [target(b, g, opt)] for i in g]
