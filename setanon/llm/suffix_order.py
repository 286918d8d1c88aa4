"""The difference-cover suffix sort as a plan: order of all suffixes of a table of strings.

Strings are rows (t, s) of symbols above 0, and a string's end is less than any symbol. Positions 1
and 2 modulo 3 are the sample.

1. The sample's triples are ranked by a range exchange; a triple's name is its place, made of the
   number of its partition and its place in there.
2. While names repeat, the names at 1 and those at 2 modulo 3 form two strings a third as long, and
   these are sorted by recursion. What one task can hold is sorted there.
3. The other positions are merged in. Against either half of the sample they compare by a key (one or
   two symbols and the rank that follows), so in the order of that key the last sampled suffix before
   each is a running maximum, carried over partition edges. The later of the two is the suffix's
   predecessor in the sample.

Equal suffixes may come in any order. Equal keys are joined, never gathered, so a suffix that very
many strings share fills no task.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, tidy, written

ORDER = ["p", "z", "a", "q"]


def suffix_array(s: np.ndarray) -> np.ndarray:
    """Start positions of the suffixes of an array of positive integers, in order."""
    n = len(s)
    if n < 3:
        return np.asarray(sorted(range(n), key=lambda i: s[i:].tolist()), np.int64)
    t = np.concatenate([s.astype(np.int64), np.zeros(3, np.int64)])
    # sample: positions 1 and 2 modulo 3 (with an empty one at n where n = 1 modulo 3)
    one, two = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)
    sample = np.concatenate([one, two])
    width = int(t.max()) + 1
    if width < 1 << 20:
        key = (t[sample] * width + t[sample + 1]) * width + t[sample + 2]
    else:
        pair = np.unique(t[sample] * width + t[sample + 1], return_inverse=True)[1]
        key = pair.astype(np.int64) * width + t[sample + 2]
    order = np.argsort(key, kind="stable")
    key = key[order]
    name = np.cumsum(np.concatenate([[1], (key[1:] != key[:-1]).astype(np.int64)]))
    del key
    if name[-1] < len(sample):  # some triples are equal: sort their names' suffixes
        names = np.empty(len(sample), np.int64)
        names[order] = name
        del order, name
        order = suffix_array(names)
        del names
    rank = np.zeros(n + 4, np.int64)
    rank[sample[order]] = np.arange(1, len(sample) + 1)
    ranked = sample[order]
    del order, sample
    ranked = ranked[ranked < n]
    # the rest: position 0 modulo 3, by first symbol and the rank that follows
    zero = np.arange(0, n, 3)
    big = n + 4
    key0 = t[zero] * big + rank[zero + 1]
    at = np.argsort(key0, kind="stable")
    zero, key0 = zero[at], key0[at]
    r1, r2 = ranked[ranked % 3 == 1], ranked[ranked % 3 == 2]
    less = np.searchsorted(t[r1] * big + rank[r1 + 1], key0)
    head = np.unique(np.concatenate([t[zero] * width + t[zero + 1], t[r2] * width + t[r2 + 1]]), return_inverse=True)[1]
    less += np.searchsorted(head[len(zero) :] * big + rank[r2 + 2], head[: len(zero)] * big + rank[zero + 2])
    out = np.full(n, -1, np.int64)
    out[np.arange(len(zero)) + less] = zero
    out[out < 0] = ranked
    return out


def _in_one_task(strings: DataFrame) -> DataFrame:
    """(t, r) for strings that are few enough for one task."""

    def run(batches):
        keys, lists = [], []
        for b in batches:
            keys += b.column(0).to_pylist()
            lists += [x.values.to_numpy() for x in b.column(1)]
        if not lists:
            return
        at = np.cumsum([0, *(len(x) + 1 for x in lists)])
        flat = np.concatenate([np.append(x, 0) for x in lists])  # the ends are the least symbol
        rank = np.empty(len(flat), np.int64)
        rank[suffix_array(np.unique(flat, return_inverse=True)[1] + 1)] = np.arange(1, len(flat) + 1)
        for t, a, b in zip(keys, at, at[1:]):
            yield pa.RecordBatch.from_arrays([pa.array([t], pa.int64()), pa.array([rank[a : b - 1]], pa.list_(pa.int64()))], ["t", "r"])
        tidy()

    return strings.repartition(1).mapInArrow(run, "t long, r array<long>")


def _places(df: DataFrame, by: list[str], parts: int, name: str) -> DataFrame:
    """The distinct rows of ``df(by)`` with their places in order."""
    d = df.select(*by).distinct().repartitionByRange(parts, *by).sortWithinPartitions(*by)
    return d.withColumn(name, F.monotonically_increasing_id() + 1)


def _last_before(cells: DataFrame, modulus: int, by: list[str], parts: int, name: str) -> DataFrame:
    """(by, name): for each key of a position 0 modulo 3, the greatest rank of the sampled ones of
    this modulus up to it, 0 if there is none."""
    which = F.col("i") % 3
    own = F.when(which == 0, F.lit(0)).otherwise(F.col("own"))
    rows = cells.where((which == 0) | (which == modulus)).select(*by, own.alias("own")).distinct()
    # of equal keys the sampled ones come first
    rows = rows.repartitionByRange(parts, *by).sortWithinPartitions(*by, F.col("own").desc())
    rows = rows.withColumn("pid", F.spark_partition_id())
    width = len(by)

    def run(batches):
        most, pid = 0, None
        for b in batches:
            own, pid = b.column(width).to_numpy(), b.column(width + 1)[0].as_py() if b.num_rows else pid
            high = np.maximum.accumulate(np.concatenate([[most], own]))[1:]
            most = int(high[-1]) if len(high) else most
            mine = own == 0
            yield pa.RecordBatch.from_arrays([*(b.column(k).filter(pa.array(mine)) for k in range(width)), pa.array(high[mine]), b.column(width + 1).filter(pa.array(mine)), pa.array(np.zeros(int(mine.sum()), bool))], [*by, "high", "pid", "last"])
        if pid is not None:  # what the partition hands on
            yield pa.RecordBatch.from_arrays([*(pa.array([0], pa.int64()) for _ in by), pa.array([most], pa.int64()), pa.array([pid], pa.int32()), pa.array([True])], [*by, "high", "pid", "last"])

    found = written(rows.mapInArrow(run, ", ".join(f"{c} long" for c in by) + ", high long, pid int, last boolean"), "merged")
    carry, edges = 0, []
    for r in found.where("last").orderBy("pid").select("pid", "high").collect():  # one row for each partition
        edges.append((r.pid, carry))
        carry = max(carry, r.high)
    edge = F.broadcast(cells.sparkSession.createDataFrame(edges, "pid int, carry long"))  # as many rows as partitions
    return found.where("NOT last").join(edge, "pid", "left").select(*by, F.greatest("high", F.coalesce("carry", F.lit(0))).alias(name))


def _keys(strings: DataFrame, parts: int, one_task: int) -> DataFrame:
    """(t, i, p, z, a, q): the order of p, z, a, q is the order of the suffixes."""
    triples = F.expr("transform(filter(sequence(0, size(s) - 1), i -> i % 3 > 0), i -> struct(i, s[i] AS a, coalesce(get(s, i + 1), 0L) AS b, coalesce(get(s, i + 2), 0L) AS c))")
    sample = strings.select("t", F.explode(triples).alias("x")).select("t", "x.*")
    names = written(_places(sample, ["a", "b", "c"], parts, "name"), "names")
    listed = F.array_sort(F.collect_list(F.struct("i", "name")))
    halves = sample.join(names, ["a", "b", "c"]).groupBy((F.col("t") * 2 + F.col("i") % 3 - 1).alias("t")).agg(F.transform(listed, lambda x: x["name"]).alias("s"))
    halves = written(halves, "halves")
    held = halves.agg(F.coalesce(F.sum(F.size("s")), F.lit(0)).alias("n"), F.coalesce(F.max(F.size("s")), F.lit(0)).alias("most")).first()
    if names.count() == held.n:
        ranks = halves.select("t", F.col("s").alias("r"))  # no name repeats
    else:
        ranks = suffix_ranks(halves, parts, one_task, held.n)
    half = F.col("t") % 2
    both = ranks.groupBy(F.shiftright("t", 1).alias("t")).agg(F.max(F.when(half == 0, F.col("r"))).alias("r1"), F.max(F.when(half == 1, F.col("r"))).alias("r2"))
    rank = lambda i: f"coalesce(CASE {i} % 3 WHEN 1 THEN get(r1, int(({i} - 1) / 3)) WHEN 2 THEN get(r2, int(({i} - 2) / 3)) END, 0L)"
    every = f"transform(sequence(0, size(s) - 1), i -> struct(i, s[i] AS a, coalesce(get(s, i + 1), 0L) AS b, {rank('(i + 1)')} AS q, {rank('(i + 2)')} AS q2, {rank('i')} AS own))"
    cells = written(strings.join(both, "t", "left").select("t", F.explode(F.expr(every)).alias("x")).select("t", "x.*"), "cells")
    one, two = _last_before(cells, 1, ["a", "q"], parts, "p1"), _last_before(cells, 2, ["a", "b", "q2"], parts, "p2")
    rest = cells.where("i % 3 = 0").join(one, ["a", "q"]).join(two, ["a", "b", "q2"]).select("t", "i", F.greatest("p1", "p2").alias("p"), F.lit(1).alias("z"), "a", "q")
    zero = F.lit(0).cast("long")
    out = written(cells.where("i % 3 > 0").select("t", "i", F.col("own").alias("p"), F.lit(0).alias("z"), zero.alias("a"), zero.alias("q")).unionByName(rest), "keys")
    for table in (names, halves, cells):
        discard(table)
    return out


def suffix_ranks(strings: DataFrame, parts: int, one_task: int, size: int | None = None) -> DataFrame:
    """(t, r): for each position of each string of ``strings(t long, s array<long>)`` the rank of the
    suffix that starts there among all suffixes."""
    if size is None:
        size = strings.agg(F.coalesce(F.sum(F.size("s")), F.lit(0))).first()[0]
    if size <= one_task:
        return written(_in_one_task(strings), "ranks")
    keys = _keys(strings, parts, one_task)
    places = written(_places(keys, ORDER, parts, "r"), "places")
    listed = F.array_sort(F.collect_list(F.struct("i", "r")))
    out = written(keys.join(places, ORDER).groupBy("t").agg(F.transform(listed, lambda x: x["r"]).alias("r")), "ranks")
    discard(keys)
    discard(places)
    return out


def repeated_windows(strings: DataFrame, length: int, parts: int, one_task: int) -> DataFrame:
    """(t, i) of the windows of ``length`` bytes of ``strings(t long, data binary)`` that occur more
    than once: suffixes in order, neighbours compared over their first ``length`` bytes."""
    spark = strings.sparkSession

    def symbols(batches):  # a byte is its value + 1, so that 0 stays free for a string's end
        for b in batches:
            lists = [np.frombuffer(d.as_buffer(), np.uint8).astype(np.int64) + 1 for d in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lists, pa.list_(pa.int64()))], ["t", "s"])

    keys = _keys(written(strings.select("t", "data").mapInArrow(symbols, "t long, s array<long>"), "symbols"), parts, one_task)
    begins = strings.select("t", "data").join(keys, "t").where(F.col("i") + length <= F.octet_length("data"))
    rows = begins.select(*ORDER, "t", "i", F.expr(f"substring(data, i + 1, {length})").alias("w"))
    by = [*ORDER, "t", "i"]
    rows = rows.repartitionByRange(parts, *by).sortWithinPartitions(*by).select("t", "i", "w", F.spark_partition_id().alias("pid"))
    schema = pa.schema([("t", pa.int64()), ("i", pa.int32()), ("pid", pa.int32()), ("edge", pa.int32()), ("w", pa.binary())])

    def run(batches):
        last, hit, first = None, False, True  # the row before, and whether it is known to repeat
        for b in batches:
            out = []
            for t, i, w, pid in zip(*(b.column(k).to_pylist() for k in range(4))):
                same = last is not None and last[2] == w
                if last is not None and (hit or same):
                    out.append((*last[:2], last[3], 0, None))
                if first:
                    out.append((t, i, pid, 1, w))
                    first = False
                last, hit = (t, i, w, pid), same
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)
        if last is not None:
            out = [(*last[:2], last[3], 0, None)] * hit + [(*last[:2], last[3], 2, last[2])]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)

    found = written(rows.mapInArrow(run, "t long, i int, pid int, edge int, w binary"), "repeats")
    edges = found.where("edge > 0").orderBy("pid", "edge").collect()  # two rows for each partition
    across = [x for a, b in zip(edges, edges[1:]) if a.edge == 2 and b.edge == 1 and a.w == b.w for x in (a, b)]
    more = spark.createDataFrame([(x.t, x.i) for x in across], "t long, i int")
    discard(keys)
    return found.where("edge = 0").select("t", "i").unionByName(more).distinct()
