"""Records as arrays and as edges; changes between two versions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.sets import canonical, item_of


def to_records(df: DataFrame, id_cols: list[str], item_cols: list[str], user: str | None = None) -> DataFrame:
    """One record for each id; several item columns become namespaced items."""
    key = F.concat_ws("@", *(F.col(c).cast("string") for c in id_cols))
    item: Column = F.col(item_cols[0]).cast("string") if len(item_cols) == 1 else F.explode(F.array(*(item_of(c, c) for c in item_cols)))
    rows = df.select(key.alias("record_id"), (F.col(user) if user else key).cast("string").alias("user_id"), item.alias("item")).where("item IS NOT NULL")
    return rows.groupBy("record_id").agg(F.min("user_id").alias("user_id"), F.array_sort(F.collect_set("item")).alias("items"))


def to_edges(recs: DataFrame) -> DataFrame:
    return recs.select("record_id", F.explode("items").alias("item"))


def from_edges(edges: DataFrame, users: DataFrame | None = None) -> DataFrame:
    recs = edges.groupBy("record_id").agg(F.array_sort(F.collect_set("item")).alias("items"))
    if users is None:
        return recs.select("record_id", F.col("record_id").alias("user_id"), "items")
    return recs.join(users.select("record_id", "user_id"), "record_id").select("record_id", "user_id", "items")


def with_attribute_items(recs: DataFrame, attributes: DataFrame, cols: dict[str, Column]) -> DataFrame:
    """Further attributes of a record as items: ``cols`` maps a namespace to a column of
    ``attributes(record_id, ...)``, already as coarse as wanted."""
    extra = attributes.select("record_id", F.explode(F.array(*(item_of(c, ns) for ns, c in cols.items()))).alias("item")).where("item IS NOT NULL")
    extra = extra.groupBy("record_id").agg(F.collect_set("item").alias("extra"))
    both = F.concat("items", F.coalesce("extra", F.array().cast("array<string>")))
    return recs.join(extra, "record_id", "left").select("record_id", "user_id", canonical(both).alias("items"))


def struct_items(df: DataFrame, key: str, cols: list[str]) -> DataFrame:
    """A row's fields as one record, an item for each field."""
    return df.select(F.col(key).cast("string").alias("record_id"), F.col(key).cast("string").alias("user_id"), canonical(F.array(*(item_of(c, c) for c in cols))).alias("items"))


def diff(before: DataFrame, after: DataFrame) -> DataFrame:
    """Edits (record_id, item, op) between two edge sets."""
    b, a = before.select("record_id", "item", F.lit(1).alias("was")), after.select("record_id", "item", F.lit(1).alias("now"))
    both = b.join(a, ["record_id", "item"], "full")
    return both.where("was IS NULL OR now IS NULL").select("record_id", "item", F.when(F.col("was").isNull(), "add").otherwise("del").alias("op"))


def apply_edits(edges: DataFrame, edits: DataFrame) -> DataFrame:
    gone = edits.where("op = 'del'").select("record_id", "item")
    new = edits.where("op = 'add'").select("record_id", "item")
    return edges.select("record_id", "item").join(gone, ["record_id", "item"], "left_anti").unionByName(new)


def multiplicity(recs: DataFrame) -> DataFrame:
    """Distinct sets and how many records hold them."""
    return recs.groupBy("items").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("user_id").alias("n_users"))


def compact(recs: DataFrame, within: str | None = None) -> DataFrame:
    """Equal sets as one weighted row with its members."""
    keys = [within, "items"] if within else ["items"]
    return recs.groupBy(*keys).agg(F.count(F.lit(1)).alias("weight"), F.array_sort(F.collect_list("record_id")).alias("members"))


def weighted(recs: DataFrame) -> DataFrame:
    """Equal sets as one row (record_id, items, weight) under the least id of its records. What
    depends on sets alone is then worked out once for all copies."""
    return recs.groupBy("items").agg(F.min("record_id").alias("record_id"), F.count(F.lit(1)).alias("weight")).select("record_id", "items", "weight")


def weight_of(recs: DataFrame) -> Column:
    """How many records a row stands for."""
    return F.col("weight") if "weight" in recs.columns else F.lit(1).cast("long")


def encode_items(edges: DataFrame, dense: bool = False) -> DataFrame:
    """Adds ``item_code``. Hashes scale; dense ranks, for small universes, go through one row per
    distinct item."""
    if not dense:
        return edges.withColumn("item_code", F.xxhash64("item"))
    from pyspark.sql import Window as W

    ranks = edges.select("item").distinct().withColumn("item_code", F.row_number().over(W.orderBy("item")).cast("long"))
    return edges.join(ranks, "item").select(*edges.columns, "item_code")
