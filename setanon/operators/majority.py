"""Costs of groups and their conversion to common sets, by counts of items in groups.

With c the records of a group that hold an item and g the group's size: the item is starred iff
0 < c < g, and costs min(c, g - c) flips.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .records import diff, to_edges


def group_counts(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, item, c, g) for items that a group holds; records may be ``weighted``."""
    g = groups.select("record_id", "group_id")
    if "weight" in recs.columns:
        rows = recs.join(g, "record_id").select("group_id", "items", "weight")
        held = rows.select("group_id", "weight", F.explode("items").alias("item")).groupBy("group_id", "item").agg(F.sum("weight").alias("c"))
        return held.join(rows.groupBy("group_id").agg(F.sum("weight").alias("g")), "group_id")
    held = to_edges(recs).join(g, "record_id").groupBy("group_id", "item").agg(F.count(F.lit(1)).alias("c"))
    return held.join(g.groupBy("group_id").agg(F.count(F.lit(1)).alias("g")), "group_id")


def star_cost(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, stars)."""
    c = group_counts(recs, groups)
    return c.groupBy("group_id").agg(F.sum(F.when(F.col("c") < F.col("g"), F.col("g")).otherwise(0)).alias("stars"))


def flip_cost(recs: DataFrame, groups: DataFrame) -> DataFrame:
    c = group_counts(recs, groups)
    return c.groupBy("group_id").agg(F.sum(F.least("c", F.col("g") - F.col("c"))).alias("flips"))


def starred(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, item, state): star or common; absent items are common zeros."""
    return group_counts(recs, groups).select("group_id", "item", F.when(F.col("c") < F.col("g"), "star").otherwise("common").alias("state"))


def targets(recs: DataFrame, groups: DataFrame, *, tie: str = "delete", ops: str = "both", weights: tuple[float, float] = (1, 1)) -> DataFrame:
    """(group_id, items) that all records of a group become. ``ops`` restricts to insertions
    (the union) or deletions (the intersection); ``weights`` price an insertion and a deletion."""
    add, drop = weights
    keep = {
        "both": (F.lit(add) * (F.col("g") - F.col("c")) <= F.lit(drop) * F.col("c")) if tie == "insert" else (F.lit(add) * (F.col("g") - F.col("c")) < F.lit(drop) * F.col("c")),
        "add": F.lit(True),
        "del": F.col("c") == F.col("g"),
    }[ops]
    kept = group_counts(recs, groups).where(keep).groupBy("group_id").agg(F.array_sort(F.collect_list("item")).alias("items"))
    every = groups.select("group_id").distinct()
    return every.join(kept, "group_id", "left").select("group_id", F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def released(groups: DataFrame, goal: DataFrame) -> DataFrame:
    """(record_id, items) after every record takes its group's set."""
    return groups.select("record_id", "group_id").join(goal, "group_id").select("record_id", "items")


def majority(recs: DataFrame, groups: DataFrame, **options) -> tuple[DataFrame, DataFrame]:
    """Targets, and the edits that lead there."""
    goal = targets(recs, groups, **options)
    inside = recs.join(groups.select("record_id"), "record_id", "left_semi")
    return goal, diff(to_edges(inside), to_edges(released(groups, goal)))


def flips_to_stars(edits: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, item) columns to star so that a flip solution becomes a star solution."""
    return edits.join(groups.select("record_id", "group_id"), "record_id").select("group_id", "item").distinct()


def expected_random_cost(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """Expected cost of a group whose centre is a random member."""
    c = group_counts(recs, groups)
    return c.groupBy("group_id").agg(F.sum(2 * F.col("c") * (F.col("g") - F.col("c")) / F.col("g")).alias("expected"))
