"""Exact set similarity join through neighbours in a common order.

Items get one order, that of their hashes. Two sets that share c of their nx + ny items, in which
nx + ny - 2c lie in one of them only, have c + 1 gaps between shared items (and the ends); each
other item lies in one gap, so at least 3c + 1 - nx - ny gaps are empty, and there both sets hold
the same two neighbours. From a Jaccard similarity of a half on that number is positive. Pairs of
neighbours hardly ever recur in sets that are not alike, where single items do: a prefix join on
them makes few candidates. Those of frequent items come late in each prefix, the ends last.

A pair of neighbours that many sets hold compares each with one of them first; sets of one class by
then need nothing more, and all others of different classes are compared. No link between classes
is lost. Equal sets are one node.
"""

from __future__ import annotations

import functools
import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import components, reliable

#: Sets of one pair of neighbours that are all compared at once.
SHORT = 8
_TOP = np.uint64(1 << 63)


def needed(total: int, t: float) -> int:
    """Least intersection of sets with ``total`` items in all that reach the similarity."""
    return math.ceil((t - 1e-9) * total / (1 + t - 1e-9) - 1e-9)


@functools.lru_cache(maxsize=1 << 16)
def prefix(n: int, t: float) -> int:
    """How many of a set's n + 1 pairs of neighbours hold one that any similar set has among its own so many."""
    sizes = range(math.ceil(t * n - 1e-6), math.floor(n / t + 1e-6) + 1)
    return n + 2 - min(3 * needed(n + m, t) + 1 - n - m for m in sizes)


#: Most frequent items whose counts every worker holds.
KNOWN = 1 << 16
NONE = (np.zeros(0, np.int64), np.zeros(0, np.int64))


def neighbours(x: np.ndarray, t: float, known: tuple[np.ndarray, np.ndarray] = NONE) -> np.ndarray:
    """The prefix of the pairs of neighbours of a sorted set: first those of rare items by the counts
    that are ``known(items, counts)``, the two ends last."""
    items, counts = known
    often = np.ones(len(x))
    if len(items):
        at = np.minimum(np.searchsorted(items, x), len(items) - 1)
        often = np.where(items[at] == x, counts[at], 1.0)
    level = np.log2(often[:-1] * often[1:]).astype(np.uint64)  # under 127
    x = x.view(np.uint64)
    inner = (x[:-1] * np.uint64(0x9E3779B97F4A7C15) ^ (x[1:] + np.uint64(0x7F4A7C15F39CC060)) * np.uint64(0xC2B2AE3D27D4EB4F)) * np.uint64(0xD6E8FEB86659FD93)
    inner = np.sort((inner ^ inner >> np.uint64(31)) >> np.uint64(8) | level << np.uint64(56))
    ends = np.sort(np.asarray([x[0] | np.uint64(1), x[-1] & ~np.uint64(1)]) | _TOP)
    return np.concatenate([inner, ends])[: prefix(len(x), t)]


def known_items(sets: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The ``KNOWN`` most frequent items and their counts; they only order what is compared."""

    def run(batches):
        for b in batches:
            flat = np.frombuffer(b"".join(b.column(0).to_pylist()), np.int64)
            item, n = np.unique(flat, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(item[n > 1]), pa.array(n[n > 1])], ["item", "n"])

    top = sets.select("ids").mapInArrow(run, "item long, n long").groupBy("item").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "item").limit(KNOWN).toArrow()
    item, n = (top.column(c).to_numpy() for c in ("item", "n"))
    order = np.argsort(item)
    return item[order], n[order]


def sketch(x: np.ndarray) -> bytes:
    """Parities of a set's items by their last bits, of about as many bits as it has items. Two
    sketches differ in at most as many bits as their sets differ in items; a long one folds."""
    size = 1 << max(7, min(13, int(0.8 * len(x)).bit_length()))
    return np.packbits(np.bincount(x & (size - 1), minlength=size).astype(np.uint8) & 1).tobytes()


def differ_at_least(x: bytes, y: bytes) -> int:
    """A lower bound of the items that lie in one of two sets only, by their sketches."""
    if len(x) < len(y):
        x, y = y, x
    if len(x) > len(y):
        x = np.bitwise_xor.reduce(np.frombuffer(x, np.uint8).reshape(-1, len(y)), axis=0).tobytes()
    return (int.from_bytes(x) ^ int.from_bytes(y)).bit_count()


def named_sets(recs: DataFrame) -> DataFrame:
    """(record_id, node, ids): the sorted hashes of each record's items as bytes, and a name of the set."""

    def run(batches):
        for b in batches:
            lists = b.column(1)
            at, flat = lists.offsets.to_numpy(), lists.values.to_numpy()
            ids = [np.unique(flat[i:j]).tobytes() for i, j in zip(at, at[1:])]
            node = [int.from_bytes(hashlib.blake2b(x, digest_size=8).digest(), "little", signed=True) for x in ids]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(node, pa.int64()), pa.array(ids, pa.binary())], ["record_id", "node", "ids"])

    hashed = recs.where(F.size("items") > 0).select("record_id", F.transform("items", lambda x: F.xxhash64(x)).alias("h"))
    return hashed.mapInArrow(run, "record_id string, node long, ids binary")


def _runs(batches, column: int):
    """Tables of whole runs of equal values, of input that is sorted by that column."""
    rest = []
    for b in batches:
        if not b.num_rows:
            continue
        key = b.column(column).to_numpy()
        first = int(np.argmax(key == key[-1]))
        if first or (rest and rest[-1].column(column)[-1].as_py() != key[0]):
            yield pa.Table.from_batches([*rest, b.slice(0, first)]) if first else pa.Table.from_batches(rest)
            rest = []
        rest.append(b.slice(first))
    if rest:
        yield pa.Table.from_batches(rest)


def _edges(key: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.r_[True, key[1:] != key[:-1], True])


MET = "g long, a long, na int, b long, nb int"


def met(sets: DataFrame, t: float) -> DataFrame:
    """(g, a, na, b, nb): pairs of nodes of short postings, with g null; of a long posting g, each
    node b (its least one too) with its least node a."""

    held = sets.sparkSession.sparkContext.broadcast(known_items(sets))  # KNOWN rows at most

    def post(batches):
        known = held.value
        for b in batches:
            parts, size = [], []
            for x in b.column(1):
                ids = np.frombuffer(x.as_buffer(), np.int64)
                parts.append(neighbours(ids, t, known))
                size.append(len(ids))
            many = [len(p) for p in parts]
            g = np.concatenate([*parts, np.zeros(0, np.uint64)]).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(g), pa.array(np.repeat(b.column(0).to_numpy(), many)), pa.array(np.repeat(np.asarray(size, np.int32), many))], ["g", "node", "n"])

    def meet(batches):
        for table in _runs(batches, 0):
            g, node, n = (table.column(c).to_numpy() for c in range(3))
            new = np.r_[True, (g[1:] != g[:-1]) | (node[1:] != node[:-1])]  # copies of a set
            g, node, n = g[new], node[new], n[new]
            edge = _edges(g)
            m = np.diff(edge)
            place = np.arange(len(g)) - np.repeat(edge[:-1], m)
            left = np.repeat(m, m)
            rows = []
            for step in range(1, SHORT):  # all pairs of short postings, those at one distance at once
                i = np.flatnonzero((left <= SHORT) & (place + step < left))
                if len(i):
                    rows.append((np.zeros(len(i), np.int64), np.ones(len(i), bool), i, i + step))
            far = np.flatnonzero(left > SHORT)
            rows.append((g[far], np.zeros(len(far), bool), np.repeat(edge[:-1], m)[far], far))
            for key, null, i, j in rows:
                key = pa.array(key, mask=null)
                yield pa.RecordBatch.from_arrays([key, pa.array(node[i]), pa.array(n[i]), pa.array(node[j]), pa.array(n[j])], ["g", "a", "na", "b", "nb"])

    posted = sets.select("node", "ids").mapInArrow(post, "g long, node long, n int")
    return posted.repartition("g").sortWithinPartitions("g", "node").mapInArrow(meet, MET)


def _sizes_fit(a, b, t: float):
    return F.least(a, b) >= F.lit(t - 1e-9) * F.greatest(a, b)


def plausible(pairs: DataFrame, sets: DataFrame, t: float) -> DataFrame:
    """The pairs (a, b) whose sketches do not rule out the similarity."""

    def draw(batches):
        for b in batches:
            ids = [np.frombuffer(x.as_buffer(), np.int64) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) for x in ids], pa.int32()), pa.array([sketch(x) for x in ids], pa.binary())], ["node", "n", "s"])

    def run(batches):
        for b in batches:
            rows = zip(*(b.column(c).to_pylist() for c in ("na", "nb", "sa", "sb")))
            keep = [differ_at_least(x, y) <= n + m - 2 * needed(n + m, t) for n, m, x, y in rows]
            yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    drawn = sets.select("node", "ids").mapInArrow(draw, "node long, n int, s binary").groupBy("node").agg(F.first("n").alias("n"), F.first("s").alias("s"))
    drawn = reliable(drawn)  # joined twice
    one, two = (drawn.select(F.col("node").alias(c), F.col("n").alias(f"n{c}"), F.col("s").alias(f"s{c}")) for c in "ab")
    return reliable(pairs.join(two, "b").join(one, "a").select("a", "b", "na", "nb", "sa", "sb").mapInArrow(run, "a long, b long"))


def verified(pairs: DataFrame, sets: DataFrame, t: float) -> DataFrame:
    """The pairs (a, b) whose whole sets reach the similarity."""
    pairs = plausible(pairs, sets, t)
    named = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    own = reliable(sets.join(named, "node", "left_semi").groupBy("node").agg(F.first("ids").alias("ids")))
    one, two = (own.select(F.col("node").alias(c), F.col("ids").alias(f"i{c}")) for c in "ab")

    def run(batches):
        for b in batches:
            keep = []
            for x, y in zip(b.column("ia"), b.column("ib")):
                x, y = np.frombuffer(x.as_buffer(), np.int64), np.frombuffer(y.as_buffer(), np.int64)
                z = np.concatenate([x, y])
                z.sort()
                keep.append(int((z[1:] == z[:-1]).sum()) >= needed(len(z), t))
            yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return reliable(pairs.join(two, "b").join(one, "a").select("a", "b", "ia", "ib").mapInArrow(run, "a long, b long"))


def _apart(long: DataFrame, found: DataFrame, t: float) -> DataFrame:
    """Pairs of nodes of different classes that share a long posting and fit in size."""
    comp = components(found).select(F.col("id").alias("b"), F.col("component_id").alias("c"))
    own = long.join(comp, "b", "left").select("g", F.col("b").alias("node"), F.col("nb").alias("n"), F.coalesce("c", "b").alias("c"))
    mixed = own.groupBy("g").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low <> high").select("g")

    def pair(batches):
        for table in _runs(batches, 0):
            g, node, n, c = (table.column(x).to_numpy() for x in range(4))
            edge = _edges(g)
            for i, j in zip(edge, edge[1:]):
                for k in range(i, j - 1):  # sorted by size
                    stop = k + 1 + int(np.searchsorted(n[k + 1 : j], n[k] / (t - 1e-9), side="right"))
                    other = node[k + 1 : stop][c[k + 1 : stop] != c[k]]
                    if len(other):
                        yield pa.RecordBatch.from_arrays([pa.array(np.minimum(other, node[k])), pa.array(np.maximum(other, node[k]))], ["a", "b"])

    rows = own.join(mixed, "g", "left_semi").repartition("g").sortWithinPartitions("g", "n", "node")
    return rows.mapInArrow(pair, "a long, b long").distinct()


def classes(recs: DataFrame, t: float) -> DataFrame:
    """(record_id, component_id) of records with items: components of the graph of similar pairs,
    each named by the least id of its records. For similarities from a half on."""
    if t < 0.5:
        raise ValueError("neighbours are sure to be shared from a similarity of a half on")
    sets = reliable(named_sets(recs))
    rows = reliable(met(sets, t).where(F.col("g").isNotNull() | _sizes_fit(F.col("na"), F.col("nb"), t)).distinct())
    tried = reliable(rows.where(F.col("a") != F.col("b")).where(_sizes_fit(F.col("na"), F.col("nb"), t)).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    found = verified(tried, sets, t)
    more = reliable(_apart(rows.where("g IS NOT NULL").select("g", "b", "nb"), found, t).join(tried, ["a", "b"], "left_anti"))
    if more.head(1):
        found = found.unionByName(verified(more, sets, t))
    comp = components(found).select(F.col("id").alias("node"), F.col("component_id").alias("c"))
    own = sets.select("record_id", "node").join(comp, "node", "left").select("record_id", F.coalesce("c", "node").alias("c"))
    return own.join(own.groupBy("c").agg(F.min("record_id").alias("component_id")), "c").select("record_id", "component_id")
