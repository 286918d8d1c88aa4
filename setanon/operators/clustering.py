"""k-group clustering on DataFrames: centres, their costs, and both directions to edits.

The minimum-load facility solver runs inside buckets, in ``kernel``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.sets import hamming
from .majority import targets
from .records import weight_of


def cluster_cost(recs: DataFrame, groups: DataFrame, centers: DataFrame) -> DataFrame:
    """(group_id, cost): sum of Hamming distances to the group's centre."""
    j = recs.join(groups.select("record_id", "group_id"), "record_id").join(centers.select("group_id", F.col("items").alias("center")), "group_id")
    return j.groupBy("group_id").agg(F.sum(hamming(F.col("items"), F.col("center"))).alias("cost"))


def best_center(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """An arbitrary set as centre: the majority of each item, optimal for a fixed group."""
    return targets(recs, groups)


def medoid(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """The member with the least sum of distances, ties by id; records may be ``weighted``.

    No pairs are made: with g members, s items in all and c members that hold an item, the distances
    to a set a sum to g |a| + s - 2 * (sum of c over a)."""
    g = recs.join(groups.select("record_id", "group_id"), "record_id")
    sets = g.groupBy("group_id", "items").agg(F.min("record_id").alias("record_id"), F.sum(weight_of(g)).alias("w"))
    cells = sets.select("group_id", "record_id", "w", F.size("items").alias("n"), F.explode_outer("items").alias("item"))
    held = cells.groupBy("group_id", "item").agg(F.sum("w").alias("c")).where("item IS NOT NULL")
    near = cells.join(held, ["group_id", "item"], "left").groupBy("group_id", "record_id", "n").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("shared"))
    whole = sets.groupBy("group_id").agg(F.sum("w").alias("g"), F.sum(F.col("w") * F.size("items")).alias("s"))
    total = near.join(whole, "group_id").select("group_id", "record_id", (F.col("g") * F.col("n") + F.col("s") - 2 * F.col("shared")).alias("d"))
    pick = total.groupBy("group_id").agg(F.min(F.struct("d", "record_id")).alias("m")).select("group_id", F.col("m.record_id").alias("record_id"), F.col("m.d").alias("cost"))
    return pick.join(recs.select("record_id", "items"), "record_id").select("group_id", "record_id", "items", "cost")


def random_center(recs: DataFrame, groups: DataFrame, seed: int = 0) -> DataFrame:
    """A member chosen by a seeded hash."""
    pick = groups.groupBy("group_id").agg(F.min_by("record_id", F.xxhash64(F.lit(seed), "record_id")).alias("record_id"))
    return pick.join(recs.select("record_id", "items"), "record_id").select("group_id", "record_id", "items")


def clusters_to_records(groups: DataFrame, centers: DataFrame) -> DataFrame:
    """Every member replaced by its centre; costs as many edits as the clustering."""
    return groups.select("record_id", "group_id").join(centers.select("group_id", "items"), "group_id").select("record_id", "items")


def groups_of(after: DataFrame) -> DataFrame:
    """A released version as a clustering of the same cost: equal sets are a group."""
    key = F.sha2(F.concat_ws("\x1f", F.array_sort("items")), 256)
    return after.select("record_id", key.alias("group_id"))
