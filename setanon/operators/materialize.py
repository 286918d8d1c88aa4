"""Token edits lifted to keywords and written back to the queries of threads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.sets import canonical, is_word, words


def cluster_keywords(threads: DataFrame, buckets: DataFrame, tokens: DataFrame, pick: str = "mode") -> DataFrame:
    """(bucket_id, token, keyword): the keyword that stands for a token in a cluster: the most
    frequent one, ties in alphabetic order; or the first, or one by hash."""
    held = threads.select(F.col("thread_id").alias("record_id"), F.explode("items").alias("keyword")).join(buckets.select("record_id", "bucket_id"), "record_id").join(tokens, "keyword")
    return _standing(held, pick)


def _standing(held: DataFrame, pick: str) -> DataFrame:
    n = held.groupBy("bucket_id", "token", "keyword").agg(F.count(F.lit(1)).alias("n"))
    order = {"mode": [F.desc("n"), F.col("keyword")], "first": [F.col("keyword")], "hash": [F.xxhash64("keyword"), F.col("keyword")]}[pick]
    return n.withColumn("r", F.row_number().over(W.partitionBy("bucket_id", "token").orderBy(*order))).where("r = 1").select("bucket_id", "token", "keyword")


def lift_edits(edits: DataFrame, threads: DataFrame, groups: DataFrame, tokens: DataFrame, pick: str = "mode") -> DataFrame:
    """(record_id, item, op) on keywords. A deleted token takes all of the thread's keywords with
    it; an inserted one brings one keyword from the thread's own cluster."""
    own = threads.select(F.col("thread_id").alias("record_id"), F.explode("items").alias("keyword")).join(tokens, "keyword")
    gone = edits.where("op = 'del'").select("record_id", F.col("item").alias("token")).join(own, ["record_id", "token"]).select("record_id", F.col("keyword").alias("item"), F.lit("del").alias("op"))
    stand = cluster_keywords(threads, groups, tokens, pick)
    new = edits.where("op = 'add'").select("record_id", F.col("item").alias("token")).join(groups.select("record_id", "bucket_id"), "record_id").join(stand, ["bucket_id", "token"])
    return gone.unionByName(new.select("record_id", F.col("keyword").alias("item"), F.lit("add").alias("op")))


def held_edits(held: DataFrame, tokens: DataFrame, pick: str = "mode") -> DataFrame:
    """``lift_edits`` of ``held(record_id, bucket_id, keywords, items, target)``, threads beside their
    solution: only threads that are edited are taken apart, and none is joined with itself."""
    edited = held.withColumn("lost", F.array_except("items", "target")).withColumn("won", F.array_except("target", "items"))
    own = edited.where(F.size("lost") > 0).select("record_id", "lost", F.explode("keywords").alias("keyword")).join(tokens, "keyword")
    gone = own.where(F.array_contains("lost", F.col("token"))).select("record_id", F.col("keyword").alias("item"), F.lit("del").alias("op"))
    new = edited.select("record_id", "bucket_id", F.explode("won").alias("token"))
    new = new.join(held_keywords(held, tokens.join(new.select("token").distinct(), "token", "left_semi"), pick), ["bucket_id", "token"])
    return gone.unionByName(new.select("record_id", F.col("keyword").alias("item"), F.lit("add").alias("op")))


def held_keywords(held: DataFrame, tokens: DataFrame, pick: str = "mode") -> DataFrame:
    """``cluster_keywords`` of threads beside their solution."""
    threads = held.select(F.col("record_id").alias("thread_id"), "bucket_id", F.col("keywords").alias("items"))
    return _standing(threads.select("bucket_id", F.explode("items").alias("keyword")).join(tokens, "keyword"), pick)


def held_spelling(held: DataFrame, tokens: DataFrame, pick: str = "mode") -> DataFrame:
    """(record_id, keyword, to): the keywords that their cluster spells otherwise. Only tokens of
    several keywords can have one."""
    several = tokens.where(is_word(F.col("keyword"))).groupBy("token").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("token")
    tokens = tokens.join(several, "token", "left_semi")
    own = held.select("record_id", "bucket_id", F.explode("keywords").alias("keyword")).join(tokens, "keyword").where(is_word(F.col("keyword")))
    stand = held_keywords(held, tokens, pick).withColumnRenamed("keyword", "to")
    return own.join(stand, ["bucket_id", "token"]).where(F.col("keyword") != F.col("to")).select("record_id", "keyword", "to")


def held_attributes() -> Column:
    """``edited_attributes`` of a thread beside its solution: an attribute item is its own token."""
    mark = lambda c: F.filter(c, lambda x: ~is_word(x))
    left = F.array_except(mark("keywords"), F.array_except("items", "target"))
    return canonical(F.concat(left, mark(F.array_except("target", "items")))).alias("attributes")


def rewrite_queries(threads: DataFrame, edits: DataFrame, canon: DataFrame | None = None) -> DataFrame:
    """(thread_id, user_id, queries): every occurrence of a deleted keyword goes, inserted ones are
    appended to the first query, queries without words vanish; attribute items never enter a text.
    ``canon(record_id, keyword, to)``
    rewrites keywords to their cluster's common spelling. ``attributes`` of the threads stay."""
    by = edits.where(is_word(F.col("item"))).groupBy("record_id").agg(F.collect_list(F.when(F.col("op") == "del", F.col("item"))).alias("gone"), F.array_sort(F.collect_list(F.when(F.col("op") == "add", F.col("item")))).alias("new"))
    none = F.array().cast("array<string>")
    t = threads.join(by.withColumnRenamed("record_id", "thread_id"), "thread_id", "left").withColumn("gone", F.coalesce("gone", none)).withColumn("new", F.coalesce("new", none))
    if canon is not None:
        pairs = canon.groupBy("record_id").agg(F.map_from_entries(F.collect_list(F.struct("keyword", "to"))).alias("to"))
        t = t.join(pairs.withColumnRenamed("record_id", "thread_id"), "thread_id", "left")
        spell = lambda w: F.coalesce(F.try_element_at(F.col("to"), w), w)
    else:
        spell = lambda w: w
    first = F.array_min(F.transform("queries", lambda q: q["seq"]))
    kept = lambda q: F.transform(F.filter(words(q["query"]), lambda w: ~F.array_contains(F.col("gone"), w)), spell)
    rewritten = F.transform("queries", lambda q: F.struct(q["seq"].alias("seq"), F.concat_ws(" ", F.when(q["seq"] == first, F.concat(kept(q), F.col("new"))).otherwise(kept(q))).alias("query")))
    return t.select("thread_id", "user_id", F.filter(rewritten, lambda q: q["query"] != "").alias("queries"), *(["attributes"] if "attributes" in threads.columns else []))


def edited_attributes(threads: DataFrame, edits: DataFrame) -> DataFrame:
    """(thread_id, attributes): a thread's attribute items after the edits."""
    ours = edits.where(~is_word(F.col("item"))).groupBy(F.col("record_id").alias("thread_id"))
    ours = ours.agg(F.collect_list(F.when(F.col("op") == "del", F.col("item"))).alias("gone"), F.collect_list(F.when(F.col("op") == "add", F.col("item"))).alias("new"))
    none = F.array().cast("array<string>")
    own = threads.select("thread_id", F.filter("items", lambda x: ~is_word(x)).alias("own")).join(ours, "thread_id", "left")
    left = F.array_except("own", F.coalesce("gone", none))
    return own.select("thread_id", canonical(F.concat(left, F.coalesce("new", none))).alias("attributes"))


def release(rewritten: DataFrame, attributes: DataFrame | None = None) -> DataFrame:
    """(thread_id, seq, query): no user, no time; seq only orders a thread's queries. With
    ``attributes(thread_id, attributes)`` these are one more column."""
    own = ["attributes"] if attributes is None and "attributes" in rewritten.columns else []
    out = rewritten.select("thread_id", *own, F.posexplode("queries").alias("seq", "q")).select("thread_id", F.col("seq").cast("long").alias("seq"), F.col("q.query").alias("query"), *own)
    return out if attributes is None else out.join(attributes, "thread_id").select("thread_id", "seq", "query", "attributes")
