"""Pairwise distances without cross joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.sets import hamming, jaccard


def pairwise(recs: DataFrame, metric: str = "hamming", within: str = "bucket_id") -> DataFrame:
    """(bucket, a, b, d) for all pairs of a bucket, by an equi-join on the bucket."""
    a = recs.select(within, F.col("record_id").alias("a"), F.col("items").alias("ia"))
    b = recs.select(within, F.col("record_id").alias("b"), F.col("items").alias("ib"))
    d = hamming(F.col("ia"), F.col("ib")) if metric == "hamming" else jaccard(F.col("ia"), F.col("ib"))
    return a.join(b, within).where("a < b").select(within, "a", "b", d.alias("d"))


def sparse_pairs(recs: DataFrame, within: str | None = None) -> DataFrame:
    """(a, b, common, d): Hamming distances of pairs that share an item, by counting common items
    over a self-join on items (and bucket)."""
    keys = ["item", *([within] if within else [])]
    e = recs.select("record_id", F.size("items").alias("n"), *([within] if within else []), F.explode("items").alias("item"))
    a = e.select(*keys, F.col("record_id").alias("a"), F.col("n").alias("na"))
    b = e.select(*keys, F.col("record_id").alias("b"), F.col("n").alias("nb"))
    both = a.join(b, keys).where("a < b").groupBy("a", "b", "na", "nb").agg(F.count(F.lit(1)).alias("common"))
    return both.select("a", "b", "common", (F.col("na") + F.col("nb") - 2 * F.col("common")).alias("d"))


def _masks(recs: DataFrame, name: str, words: int) -> DataFrame:
    """(name, one column of 64 bits for each run of 64 places) of ``recs(record_id, places)``."""
    bit = lambda m, x: m.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), x % 64))
    own = lambda w: F.filter("places", lambda x: F.floor(x / 64) == w)
    return recs.select(F.col("record_id").alias(name), *(F.aggregate(own(w), F.lit(0).cast("long"), bit).alias(f"{name}{w}") for w in range(words)))


def search(queries: DataFrame, recs: DataFrame) -> DataFrame:
    """(a, b, common, d): Hamming distances of each query to all other records that share a place
    with it. Sets are ``places``, arrays of small numbers: each is a few words of bits, and a pair is
    a few machine steps in a loop over the queries, which every task holds. The result has a row for
    nearly each query and record where sets are dense, so no join on places would make fewer."""
    top = recs.agg(F.max(F.array_max("places")).alias("p")).first()[0]
    words = 1 + (top or 0) // 64
    a, b = _masks(queries, "a", words), _masks(recs, "b", words)
    count = lambda c: F.bit_count(c).cast("int")
    total = lambda cols: sum(cols[1:], cols[0])
    both = total([count(F.col(f"a{w}").bitwiseAND(F.col(f"b{w}"))) for w in range(words)])
    shares = total([(F.col(f"a{w}").bitwiseAND(F.col(f"b{w}")) != 0).cast("int") for w in range(words)]) > 0
    apart = total([count(F.col(f"a{w}").bitwiseXOR(F.col(f"b{w}"))) for w in range(words)])
    pairs = b.join(F.broadcast(a), shares & (F.col("a") != F.col("b")))  # of a query its id and its bits
    return pairs.select("a", "b", both.alias("common"), apart.alias("d"))


def knn(recs: DataFrame, k: int, within: str | None = None) -> DataFrame:
    """(record_id, other, d, place): the k nearest others, ties by id. Inside a bucket all pairs
    count; without one, pairs that share an item."""
    p = pairwise(recs, within=within) if within else sparse_pairs(recs)
    both = p.select(F.col("a").alias("record_id"), F.col("b").alias("other"), "d").unionByName(p.select(F.col("b").alias("record_id"), F.col("a").alias("other"), "d"))
    return both.withColumn("place", F.row_number().over(W.partitionBy("record_id").orderBy("d", "other"))).where(F.col("place") <= k)
