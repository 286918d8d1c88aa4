"""Sessions of a query log cut into topic threads.

A log is (user_id, ts, seq, query); rows are ordered by (ts, seq). All joins are equi-joins on
the user, and strings are compared once for each distinct pair of a user's queries.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import secret_id
from ..functions.sets import words
from .graph import reliable, roots
from .searchsim import overlapping_pairs, result_lists


@dataclass(frozen=True)
class ThreadOptions:
    edit_threshold: int = 4  # distances strictly below are similar
    top: int = 50
    min_overlap: int = 20
    similarity: str = "edit"  # edit, results or any


def sim_edit(a: Column, b: Column, threshold: int) -> Column:
    """Edit distance strictly below the threshold. The bounded form stops early, and lengths that
    differ too much are not compared at all."""
    near = F.abs(F.length(a) - F.length(b)) < threshold
    return near & (F.levenshtein(a, b, threshold - 1) >= 0)


def _lists(log: DataFrame, o: ThreadOptions, corpus: DataFrame | None) -> DataFrame:
    if corpus is None:
        raise ValueError("result overlap needs a corpus")
    return reliable(result_lists(log.select("query"), corpus, o.top))  # joined twice, and each would match all blocks again


def similar_queries(log: DataFrame, o: ThreadOptions = ThreadOptions(), corpus: DataFrame | None = None) -> DataFrame:
    """(user_id, qa, qb) in both directions, for distinct queries of one user that are similar; a
    query is similar to itself."""
    q = log.select("user_id", "query").distinct()
    a, b = q.withColumnRenamed("query", "qa"), q.withColumnRenamed("query", "qb")
    own = a.join(b, "user_id").where("qa < qb")
    near = own.where(sim_edit(F.col("qa"), F.col("qb"), o.edit_threshold)) if o.similarity in ("edit", "any") else own.where("false")
    if o.similarity in ("results", "any"):
        hits = overlapping_pairs(own.select("qa", "qb").distinct(), _lists(log, o, corpus), o.min_overlap)
        near = near.unionByName(own.join(hits, ["qa", "qb"]).select("user_id", "qa", "qb")).distinct()
    back = near.select("user_id", F.col("qb").alias("qa"), F.col("qa").alias("qb"))
    return near.unionByName(back).unionByName(q.select("user_id", F.col("query").alias("qa"), F.col("query").alias("qb")))


#: A column of a log, an array of attribute items, that goes along with its rows into ``thread_sets``.
ATTRIBUTES = "_attributes"


def _numbered(log: DataFrame) -> DataFrame:
    order = W.partitionBy("user_id").orderBy("ts", "seq", "query")
    more = [ATTRIBUTES] if ATTRIBUTES in log.columns else []
    return log.select("user_id", "ts", "seq", "query", *more).withColumn("at", F.row_number().over(order))


def parents(log: DataFrame, similar: DataFrame) -> DataFrame:
    """(user_id, at, ts, seq, query, parent): the place of the most recent similar predecessor."""
    rows = _numbered(log)
    # places of each query of a user, so that the latest one before a row is an array step
    places = rows.groupBy("user_id", "query").agg(F.array_sort(F.collect_list("at")).alias("places"))
    near = similar.join(places.withColumnRenamed("query", "qb"), ["user_id", "qb"]).select("user_id", F.col("qa").alias("query"), "places")
    j = rows.join(near, ["user_id", "query"]).withColumn("p", F.array_max(F.filter("places", lambda x: x < F.col("at"))))
    return j.groupBy("user_id", "at").agg(F.any_value("ts").alias("ts"), F.any_value("seq").alias("seq"), F.any_value("query").alias("query"), F.max("p").alias("parent"))


def first_pass(log: DataFrame, similar: DataFrame) -> DataFrame:
    """(user_id, at, ts, seq, query, root): threads named by the place of their first query."""
    p = reliable(parents(log, similar))
    name = lambda c: F.concat_ws("\x1f", "user_id", F.col(c).cast("string"))
    r = roots(p.select(name("at").alias("node"), F.when(F.col("parent").isNotNull(), name("parent")).alias("parent")))
    return p.withColumn("node", name("at")).join(r, "node").select("user_id", "at", "ts", "seq", "query", F.substring_index("root", "\x1f", -1).cast("int").alias("root"))


def collapse(threads: DataFrame, similar: DataFrame) -> DataFrame:
    """Merges runs of consecutive threads of a user that hold a similar pair, to a fixpoint."""
    now = reliable(threads)
    while True:  # each round leaves fewer threads
        first = now.select("user_id", "root").distinct().withColumn("before", F.lag("root").over(W.partitionBy("user_id").orderBy("root")))
        q = now.select("user_id", "root", "query").distinct()
        near = (
            first.where("before IS NOT NULL")
            .join(q.withColumnRenamed("query", "qa"), ["user_id", "root"])
            .join(similar, ["user_id", "qa"])
            .join(q.select("user_id", F.col("root").alias("before"), F.col("query").alias("qb")), ["user_id", "before", "qb"])
            .select("user_id", "root")
            .distinct()
            .withColumn("joins", F.lit(True))
        )
        if not near.head(1):
            break
        run = F.max(F.when(F.col("joins").isNull(), F.col("root"))).over(W.partitionBy("user_id").orderBy("root").rowsBetween(W.unboundedPreceding, 0))
        named = first.join(near, ["user_id", "root"], "left").withColumn("new", run).select("user_id", "root", "new")
        now = reliable(now.join(named, ["user_id", "root"]).select("user_id", "at", "ts", "seq", "query", F.col("new").alias("root")))
    return now


#: Logs of at most so many different queries are cut in one pass; all their pairs are compared once.
FEW = 2_048


def assign_threads(log: DataFrame, o: ThreadOptions = ThreadOptions(), corpus: DataFrame | None = None) -> DataFrame:
    queries = log.select("query").distinct().where("query IS NOT NULL")
    few = [r[0] for r in queries.limit(FEW + 1).collect()]
    if len(few) <= FEW:
        return _cut_few(log, sorted(few), o, corpus)
    similar = reliable(similar_queries(log, o, corpus))
    return collapse(first_pass(log, similar), similar)


def similar_matrix(spark, queries: list[str], o: ThreadOptions, corpus: DataFrame | None) -> np.ndarray:
    """Which of some different queries are similar: each to itself, and pairs in both directions."""
    q = spark.createDataFrame(list(enumerate(queries)), "i int, query string")
    a, b = q.select(F.col("i").alias("ia"), F.col("query").alias("qa")), q.select(F.col("i").alias("ib"), F.col("query").alias("qb"))
    pairs = a.join(F.broadcast(b), F.col("ia") < F.col("ib"))  # FEW rows on both sides
    out = np.eye(len(queries), dtype=bool)
    code = {x: i for i, x in enumerate(queries)}
    near = []
    if o.similarity in ("edit", "any"):
        near.append(pairs.where(sim_edit(F.col("qa"), F.col("qb"), o.edit_threshold)).select("qa", "qb"))
    if o.similarity in ("results", "any"):
        near.append(overlapping_pairs(pairs.select("qa", "qb"), _lists(q, o, corpus), o.min_overlap))
    for rows in near:
        hit = rows.toArrow()  # FEW squared at most
        x, y = ([code[v] for v in hit.column(c).to_pylist()] for c in ("qa", "qb"))
        out[x, y] = out[y, x] = True
    return out


def first_roots(codes: np.ndarray, start: np.ndarray, near: np.ndarray, cells: int = 1 << 22) -> np.ndarray:
    """For rows of users, one after the other from ``start`` on, the place in its user's rows of the
    first query of each one's thread, from 0. All users take a step at once: ``last`` holds for each
    user and query the latest row that is similar to it."""
    length, root = np.diff(start), np.zeros(len(codes), np.int64)
    order = np.argsort(-length, kind="stable")
    step = max(1, cells // max(1, len(near)))
    for a in range(0, len(order), step):
        users = order[a : a + step]
        last = np.full((len(users), len(near)), -1, np.int32)
        at, size = start[:-1][users], length[users]
        for t in range(int(size[0])):
            m = int(np.searchsorted(-size, -t))  # users with more than t rows
            row = at[:m] + t
            q = codes[row]
            parent = last[np.arange(m), q]
            root[row] = np.where(parent < 0, t, root[at[:m] + parent])
            last[:m][near[q]] = t
    return root


def merged_roots(codes: list[int], root: list[int], near: list[int]) -> list[int]:
    """One user's threads with runs of neighbours merged that hold a similar pair, to a fixpoint.
    Sets of queries are bits of a number."""
    while True:  # each round leaves fewer threads
        held: dict[int, int] = {}
        for r, q in zip(root, codes):
            held[r] = held.get(r, 0) | near[q] << len(near) | 1 << q
        new, before, goal = {}, 0, -1
        for r in sorted(held):
            if not held[r] >> len(near) & before:
                goal = r
            new[r], before = goal, held[r] & (1 << len(near)) - 1
        if len(held) == len(set(new.values())):
            return root
        root = [new[r] for r in root]


def distinct_queries(log: DataFrame, o: ThreadOptions = ThreadOptions(), corpus: DataFrame | None = None) -> DataFrame:
    """(user_id, root, q, n): the different queries of each thread of ``assign_threads``, in order, and
    the number of its rows. Where a user's rows are cut they are folded too, so no row moves again."""
    few = [r[0] for r in log.select("query").distinct().where("query IS NOT NULL").limit(FEW + 1).collect()]
    if len(few) <= FEW:
        return _cut_few(log, sorted(few), o, corpus, fold=True)
    return assign_threads(log, o, corpus).groupBy("user_id", "root").agg(F.sort_array(F.collect_set("query")).alias("q"), F.count(F.lit(1)).alias("n"))


def _folded(start: np.ndarray, codes: np.ndarray, root: np.ndarray, user: pa.Array, queries: list[str]) -> pa.RecordBatch:
    valid = codes < len(queries)
    which = np.repeat(np.arange(len(start) - 1), np.diff(start))[valid]
    thread, at = np.unique(which * (int(root.max(initial=0)) + 1) + root[valid], return_inverse=True)
    pairs = np.unique(at * max(1, len(queries)) + codes[valid])
    of, code = np.divmod(pairs, max(1, len(queries)))
    first = np.searchsorted(of, np.arange(len(thread) + 1))
    users, roots = np.divmod(thread, int(root.max(initial=0)) + 1)
    q = pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(queries, pa.string()).take(pa.array(code)))
    n = np.bincount(at, minlength=len(thread))
    return pa.RecordBatch.from_arrays([user.take(pa.array(start[:-1][users])), pa.array(roots + 1, pa.int32()), q, pa.array(n, pa.int64())], ["user_id", "root", "q", "n"])


def _cut_few(log: DataFrame, queries: list[str], o: ThreadOptions, corpus: DataFrame | None, fold: bool = False) -> DataFrame:
    """The threads of a log of few different queries. A user's rows are read in order, once; a task
    holds an Arrow batch and the rows of one user."""
    spark = log.sparkSession
    near = similar_matrix(spark, queries, o, corpus)
    near = np.pad(near, (0, 1))  # no query is a code of its own, similar to none
    bits = [sum(1 << int(x) for x in np.flatnonzero(row)) for row in near]
    held = spark.sparkContext.broadcast((queries, near, bits))
    names = ["user_id", "at", "ts", "seq", "query", "root"]

    def cut(rows: pa.Table) -> pa.RecordBatch:
        queries, near, bits = held.value
        rows = rows.combine_chunks()
        user, query = (rows.column(c).chunk(0) for c in ("user_id", "query"))
        start = np.r_[0, np.flatnonzero(pc.not_equal(user[1:], user[:-1]).to_numpy(zero_copy_only=False)) + 1, len(user)]
        codes = pc.fill_null(pc.index_in(query, pa.array(queries)), len(queries)).to_numpy(zero_copy_only=False)
        root = first_roots(codes, start, near)
        c, r = codes.tolist(), root.tolist()
        for a, b in zip(start[:-1].tolist(), start[1:].tolist()):
            r[a:b] = merged_roots(c[a:b], r[a:b], bits)
        if fold:
            return _folded(start, codes, np.asarray(r), user, queries)
        at = np.arange(len(user)) - np.repeat(start[:-1], np.diff(start))
        out = [user, pa.array(at + 1, pa.int32()), rows.column("ts").chunk(0), rows.column("seq").chunk(0), query, pa.array(np.asarray(r) + 1, pa.int32())]
        return pa.RecordBatch.from_arrays(out, names).filter(pc.is_valid(query))

    def run(batches):
        rest = []
        for batch in batches:
            if not batch.num_rows:
                continue
            user = batch.column(0)
            same = pc.equal(user, user[-1]).to_numpy(zero_copy_only=False)
            first = int(np.argmax(same))  # sorted by user: the last one may go on
            if rest and (first or rest[-1].column(0)[-1] != user[-1]):
                yield cut(pa.Table.from_batches([*rest, batch.slice(0, first)]))
                rest = []
            elif first:
                yield cut(pa.Table.from_batches([batch.slice(0, first)]))
            rest.append(batch.slice(first))
        if rest:
            yield cut(pa.Table.from_batches(rest))

    rows = log.select("user_id", "ts", "seq", "query").where("user_id IS NOT NULL")
    rows = rows.repartition("user_id").sortWithinPartitions("user_id", "ts", "seq", "query")
    types = dict(log.dtypes)
    if fold:
        return rows.mapInArrow(run, "user_id string, root int, q array<string>, n long")
    return rows.mapInArrow(run, f"user_id string, at int, ts {types['ts']}, seq {types['seq']}, query string, root int")


def assign_threads_kernel(log: DataFrame, similar: DataFrame) -> DataFrame:
    """The same threads by one Arrow kernel for each user; for users of bounded size."""
    near = similar.groupBy("user_id", "qa").agg(F.collect_list("qb").alias("near")).withColumnRenamed("qa", "query")
    rows = _numbered(log).join(near, ["user_id", "query"]).select("user_id", "at", "ts", "seq", "query", "near")

    def run(table):
        table = table.sort_by("at")
        queries, near = table.column("query").to_pylist(), [set(x) for x in table.column("near").to_pylist()]
        last, root = {}, []
        for i, q in enumerate(queries):
            seen = [last[x] for x in near[i] if x in last]
            root.append(root[max(seen)] if seen else i + 1)
            last[q] = i
        while True:  # each round leaves fewer threads
            members: dict[int, list[int]] = {}
            for i, r in enumerate(root):
                members.setdefault(r, []).append(i)
            order, new, before = sorted(members), {}, None
            for r in order:
                joins = before is not None and any(queries[j] in near[i] for i in members[r] for j in members[before])
                new[r] = new[before] if joins else r
                before = r
            if all(a == b for a, b in new.items()):
                break
            root = [new[r] for r in root]
        return table.drop_columns(["near"]).append_column("root", pa.array(root, pa.int32()))

    return rows.groupBy("user_id").applyInArrow(run, "user_id string, at int, ts timestamp, seq long, query string, root int")


def sessions(log: DataFrame) -> DataFrame:
    """No split: a user's whole session is one thread."""
    return _numbered(log).withColumn("root", F.lit(1))


def threads_singleton(log: DataFrame) -> DataFrame:
    """Every query is a thread of its own."""
    return _numbered(log).withColumn("root", F.col("at"))


def threads_by_gap(log: DataFrame, seconds: int) -> DataFrame:
    """A thread ends where a user pauses for longer than the gap."""
    w = W.partitionBy("user_id").orderBy("at")
    gap = F.unix_timestamp("ts") - F.unix_timestamp(F.lag("ts").over(w))
    start = _numbered(log).withColumn("starts", F.coalesce(gap > seconds, F.lit(True)))
    return start.withColumn("root", F.max(F.when(F.col("starts"), F.col("at"))).over(w)).drop("starts")


def relabel(threads: DataFrame, secret: str) -> DataFrame:
    """Adds ``thread_id``, a keyed hash: stable for the holder of the secret, unlinkable for others."""
    return threads.withColumn("thread_id", secret_id(secret, "user_id", "root"))


def keyword_sets(threads: DataFrame) -> DataFrame:
    """(record_id, items, weight): the distinct keyword sets of threads as ``weighted`` records, for
    measures that need neither texts nor published ids. Threads are cut where their user's rows are,
    and words once for each distinct set of queries."""
    q = threads.groupBy("user_id", "root").agg(F.sort_array(F.collect_set("query")).alias("q"))
    q = q.groupBy("q").agg(F.min(F.concat_ws("/", "user_id", F.col("root").cast("string"))).alias("record_id"), F.count(F.lit(1)).alias("n"))
    items = F.array_sort(F.array_distinct(F.flatten(F.transform("q", lambda x: words(x)))))
    return q.select("record_id", "n", items.alias("items")).groupBy("items").agg(F.min("record_id").alias("record_id"), F.sum("n").alias("weight")).select("record_id", "items", "weight")


def thread_sets(threads: DataFrame, named: bool = True) -> DataFrame:
    """(thread_id, user_id, items, queries): unique keywords; stop words stay. Threads are folded where
    their user's rows are, and a query that recurs in a thread is cut into words once. Those that are
    not ``named`` have their place, ``root``, instead of an id."""
    own = [F.flatten(F.collect_set(ATTRIBUTES)).alias(ATTRIBUTES)] if ATTRIBUTES in threads.columns else []
    folded = threads.groupBy("user_id", "root").agg(*([F.any_value("thread_id").alias("thread_id")] if named else []), F.array_sort(F.collect_list(F.struct("seq", "query"))).alias("queries"), *own)
    items = F.array_sort(F.array_distinct(F.flatten(F.transform(F.array_distinct(F.transform("queries", lambda x: x["query"])), lambda x: words(x)))))
    return folded.select("thread_id" if named else "root", "user_id", items.alias("items"), "queries", *([ATTRIBUTES] if own else []))
