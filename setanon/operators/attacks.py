"""What an attacker with partial knowledge can do."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .records import to_edges, weighted


def known_items(recs: DataFrame, known: int, of: int, exclude_top: int = 0, seed: int = 0) -> DataFrame:
    """(victim, item): for each record, ``known`` of ``of`` of its items outside the globally most
    frequent ``exclude_top``, chosen by hash. Records with fewer than ``of`` are left out."""
    e = to_edges(recs)
    top = e.groupBy("item").count().orderBy(F.desc("count"), "item").limit(exclude_top).select("item")
    rest = e.join(F.broadcast(top), "item", "left_anti") if exclude_top else e  # a stated number of items
    h = F.md5(F.concat_ws("|", F.lit(str(seed)), "record_id", "item"))
    w = W.partitionBy("record_id")
    rows = rest.withColumn("r", F.row_number().over(w.orderBy(h, "item"))).withColumn("n", F.count(F.lit(1)).over(w))
    return rows.where((F.col("n") >= of) & (F.col("r") <= known)).select(F.col("record_id").alias("victim"), "item")


def candidates(facts: DataFrame, released: DataFrame, known: int) -> DataFrame:
    """(victim, candidates): released records that hold all the known items.

    Victims of the same known items are asked once, and equal released sets are looked at once: the
    known items' rarest one leads to sets, which are then checked for the others."""
    asked = facts.groupBy("victim").agg(F.sort_array(F.collect_set("item")).alias("facts"))
    kinds = asked.where(F.size("facts") == known).select("facts").distinct()
    sets = weighted(released)
    cells = to_edges(sets)
    often = cells.groupBy("item").agg(F.count(F.lit(1)).alias("n"))
    rarest = kinds.select("facts", F.explode("facts").alias("item")).join(often, "item", "left")
    rarest = rarest.groupBy("facts").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "item")).alias("m")).select("facts", F.col("m.item").alias("item"))
    hit = rarest.join(cells, "item").join(sets, "record_id").where(F.size(F.array_except("facts", "items")) == 0)
    n = hit.groupBy("facts").agg(F.sum("weight").alias("candidates"))
    return asked.join(n, "facts", "left").select("victim", F.coalesce("candidates", F.lit(0)).alias("candidates"))


def attack_rate(recs: DataFrame, released: DataFrame, known: int = 6, of: int = 8, exclude_top: int = 500, seed: int = 0) -> DataFrame:
    """One row: victims, those with a single candidate, and their share."""
    c = candidates(known_items(recs, known, of, exclude_top, seed), released, known)
    n, one = F.count(F.lit(1)), F.count_if(F.col("candidates") == 1)
    return c.agg(n.alias("victims"), one.alias("unique_matches"), F.round(one / F.greatest(n, F.lit(1)), 6).alias("rate"))


def stitch_risk(threads: DataFrame, rare: int = 5) -> DataFrame:
    """One row: pairs of threads that share an item held by at most ``rare`` threads, how many of
    them are one user's, and the share."""
    e = threads.select("record_id", "user_id", F.explode("items").alias("item"))
    few = e.groupBy("item").count().where((F.col("count") > 1) & (F.col("count") <= rare)).select("item")
    k = e.join(few, "item")
    a, b = (k.select("item", F.col("record_id").alias(f"r{i}"), F.col("user_id").alias(f"u{i}")) for i in "ab")
    p = a.join(b, "item").where("ra < rb").select("ra", "rb", "ua", "ub").distinct()
    n, same = F.count(F.lit(1)), F.count_if(F.col("ua") == F.col("ub"))
    return p.agg(n.alias("pairs"), same.alias("same_user"), F.round(same / F.greatest(n, F.lit(1)), 6).alias("rate"))
