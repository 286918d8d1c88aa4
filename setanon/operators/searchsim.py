"""A lexical search simulator for result overlap."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.sets import words

#: Sets of words and queries that one task matches, and asked words up to which the corpus is narrowed first.
SETS, QUERIES, SMALL = 1 << 15, 250_000, 200_000
#: Between the words of a set in one string; no word holds it.
SEP = "\x1f"


def best_docs(queries: list[str], texts: pa.Array, docs: pa.ListArray, n: int) -> pa.Table:
    """(words, docs, matched): for each query its n best documents of a block, those that hold most of its
    words first, ties by id. Texts are sets of words, ``docs`` the n least ids of each in order.

    A word that many sets hold is a row of zeros and ones, the others are lists of sets; a query adds
    the rows and lists of its words."""
    order = pc.sort_indices(pc.list_element(docs, 0))  # by the least id, so that ties are in order
    docs = docs.take(order)
    split = pc.split_pattern(texts.take(order), SEP)
    code = split.flatten().dictionary_encode()
    where = pc.list_parent_indices(split).to_numpy()
    word = code.indices.to_numpy()
    by = np.argsort(word, kind="stable")
    held = where[by].astype(np.int32)
    edge = np.searchsorted(word[by], np.arange(len(code.dictionary) + 1))
    at = dict(zip(code.dictionary.to_pylist(), range(len(code.dictionary))))
    many, size = np.flatnonzero(np.diff(edge) * 16 > len(docs)), len(docs)
    kind = np.uint8 if max((q.count(SEP) for q in queries), default=0) < 255 else np.uint16
    rows = {}
    for w in many.tolist():
        rows[w] = np.zeros(size, kind)
        rows[w][held[edge[w] : edge[w + 1]]] = 1
    first, ids = docs.offsets.to_numpy(), docs.values.to_numpy()
    first, ids = first - first[0], ids[first[0] : first[-1]]
    many_docs = np.diff(first)
    single = len(ids) == size
    told, found, matched = [], [], []
    for q in queries:
        count = np.zeros(size, kind)
        for w in q.split(SEP):
            w = at.get(w)
            if w in rows:
                count += rows[w]
            elif w is not None:
                count[held[edge[w] : edge[w + 1]]] += 1
        value, above = int(count.max(initial=0)), 0
        if not value:
            continue
        while value > 1 and (above := above + np.count_nonzero(count == value)) < n:
            value -= 1
        over = np.flatnonzero(count > value)  # fewer than n
        over = over[np.argsort(-count[over].astype(np.int32), kind="stable")]
        sets = np.r_[over, np.flatnonzero(count == value)[: n - len(over)]]  # a set further on has n better ids before it
        hits = count[sets].astype(np.int32)
        if single:
            mine = ids[sets]
        else:
            hits = np.repeat(hits, many_docs[sets])
            mine = np.concatenate([ids[first[s] : first[s + 1]] for s in sets])
            best = np.lexsort((mine, -hits))[:n]
            mine, hits = mine[best], hits[best]
        told.append(q)
        found.append(mine)
        matched.append(hits)
    ends = np.cumsum([0, *map(len, found)]).astype(np.int32)
    none = np.zeros(0, np.int64)
    flat, hits = pa.array(np.concatenate([none, *found])), pa.array(np.concatenate([none.astype(np.int32), *matched]))
    return pa.table({"words": pa.array(told, pa.string()), "docs": pa.ListArray.from_arrays(ends, flat), "matched": pa.ListArray.from_arrays(ends, hits)})


#: Asked words up to which a document's set of them is kept as bits.
FEW = 496


def _few_words(corpus: DataFrame, few: list[str]) -> DataFrame:
    """(doc, words): the asked words of each document as bits of numbers, 62 in each."""
    code = corpus.sparkSession.createDataFrame([(w, i // 62, 1 << i % 62) for i, w in enumerate(few)], "word string, part int, bit long")
    bits = [F.coalesce(F.bit_or(F.when(F.col("part") == i, F.col("bit"))), F.lit(0).cast("long")) for i in range(-(-len(few) // 62))]
    return corpus.join(F.broadcast(code), "word").groupBy("doc").agg(F.array(*bits).alias("words"))


def result_lists(queries: DataFrame, corpus: DataFrame, n: int = 50) -> DataFrame:
    """(query, docs): the n documents that match most distinct words of a query, ties by id, best first.
    ``corpus(doc, word)`` is an inverted index; each distinct set of words is looked up once.

    Documents of the same asked words match alike, so they are one set with its n least ids. Blocks
    of sets meet blocks of queries in a task, and a query's blocks are merged."""
    spark = queries.sparkSession
    q = queries.select("query").distinct().select("query", F.array_sort(F.array_distinct(words(F.col("query")))).alias("w")).where(F.size("w") > 0)
    q = q.select("query", F.concat_ws(SEP, "w").alias("words")).persist(StorageLevel.DISK_ONLY)
    asked = q.select(F.explode(F.split("words", SEP)).alias("word")).distinct()
    few = sorted(r[0] for r in asked.limit(FEW + 1).collect())
    if len(few) <= FEW:
        sets = _few_words(corpus, few)
    else:
        if asked.limit(SMALL + 1).count() <= SMALL:
            corpus = corpus.join(F.broadcast(asked), "word", "left_semi")
        sets = corpus.groupBy("doc").agg(F.concat_ws(SEP, F.sort_array(F.collect_set("word"))).alias("words"))
    sets = sets.withColumnRenamed("words", "set")
    least = F.row_number().over(W.partitionBy("set").orderBy("doc"))
    sets = sets.withColumn("_r", least).where(F.col("_r") <= n).groupBy("set").agg(F.sort_array(F.collect_list("doc")).alias("docs"))
    if len(few) <= FEW:
        held = F.filter(F.array(*map(F.lit, few)), lambda x, i: F.getbit(F.get("set", F.floor(i / 62).cast("int")), i % 62) == 1)
        sets = sets.select(F.concat_ws(SEP, held).alias("words"), "docs")
    else:
        sets = sets.withColumnRenamed("set", "words")
    sets = sets.persist(StorageLevel.DISK_ONLY)
    kinds = q.select("words").distinct()
    n_sets, n_kinds, cores = sets.count(), kinds.count(), spark.sparkContext.defaultParallelism
    across = max(1, -(-n_sets // SETS))
    down = max(-(-n_kinds // QUERIES), min(-(-cores // across), -(-n_kinds // 4096)), 1)
    place = lambda n: F.pmod(F.xxhash64("words"), F.lit(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    sets = sets.withColumn("_d", place(across)).withColumn("_q", each(down))
    kinds = kinds.withColumn("_q", place(down)).withColumn("_d", each(across))

    def run(asked: pa.Table, block: pa.Table) -> pa.Table:
        block = block.combine_chunks()
        one = [block.column(c).chunk(0) if block.num_rows else block.schema.field(c).type for c in ("words", "docs")]
        texts, docs = (pa.array([], x) if isinstance(x, pa.DataType) else x for x in one)
        return best_docs(asked.column("words").to_pylist(), texts, docs, n)

    part = kinds.groupBy("_q", "_d").cogroup(sets.groupBy("_q", "_d")).applyInArrow(run, "words string, docs array<long>, matched array<int>")
    if across > 1:
        pairs = F.arrays_zip(F.transform("matched", lambda x: -x).alias("m"), F.col("docs").alias("d"))
        merged = F.slice(F.sort_array(F.flatten(F.collect_list(pairs))), 1, n)
        part = part.groupBy("words").agg(merged.alias("x")).select("words", F.col("x.d").alias("docs"))
    return q.join(part.select("words", "docs"), "words").select("query", "docs")


def top_results(queries: DataFrame, corpus: DataFrame, n: int = 50) -> DataFrame:
    """(query, doc, place) of ``result_lists``."""
    return result_lists(queries, corpus, n).select("query", F.posexplode("docs").alias("place", "doc")).select("query", "doc", (F.col("place") + 1).alias("place"))


def overlapping(results: DataFrame, min_overlap: int) -> DataFrame:
    """(qa, qb, shared) of queries whose lists share enough results: an equi-join on the result and
    a count, never a cross join."""
    a, b = results.select("doc", F.col("query").alias("qa")), results.select("doc", F.col("query").alias("qb"))
    return a.join(b, "doc").where("qa < qb").groupBy("qa", "qb").agg(F.count(F.lit(1)).alias("shared")).where(F.col("shared") >= min_overlap)


def overlapping_pairs(pairs: DataFrame, lists: DataFrame, min_overlap: int) -> DataFrame:
    """The given pairs (qa, qb) whose ``result_lists`` share enough results."""
    both = pairs.join(lists.select(F.col("query").alias("qa"), F.col("docs").alias("da")), "qa").join(lists.select(F.col("query").alias("qb"), F.col("docs").alias("db")), "qb")
    return both.where(F.size(F.array_intersect("da", "db")) >= min_overlap).select("qa", "qb")
