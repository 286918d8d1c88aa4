"""Schemas of the fixed table shapes, and their checks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RECORDS = "record_id string, user_id string, items array<string>"
EDGES = "record_id string, item string"
LOG = "user_id string, ts timestamp, seq long, query string"
THREADS = "thread_id string, user_id string, items array<string>, queries array<struct<seq:long,query:string>>"
GROUPS = "record_id string, bucket_id string, group_id string"
TARGETS = "group_id string, items array<string>"
EDITS = "record_id string, item string, op string"
COST = "metric string, value double"


class InvalidRecords(ValueError):
    pass


def validate(df: DataFrame, kind: str, *, on_empty_input: str = "error") -> DataFrame:
    """Check records or edges: no null id or item, no repeated edge or record, no empty set.

    ``on_empty_input="drop"`` filters empty sets instead of failing. One aggregation runs.
    """
    if kind == "edges":
        bad = df.agg(
            F.count_if(F.col("record_id").isNull() | F.col("item").isNull()).alias("nulls"),
            (F.count(F.lit(1)) - F.count_distinct("record_id", "item")).alias("repeats"),
        ).first()
        if bad.nulls or bad.repeats:
            raise InvalidRecords(f"{bad.nulls} null ids or items, {bad.repeats} repeated edges")
        return df
    if kind != "records":
        raise ValueError(f"unknown kind {kind}")
    none = F.col("items").isNull() | (F.size("items") == 0)
    bad = df.agg(
        F.count_if(F.col("record_id").isNull() | F.exists(F.coalesce("items", F.array().cast("array<string>")), lambda x: x.isNull())).alias("nulls"),
        F.count_if(none).alias("empty"),
        F.count_if(F.size(F.array_distinct("items")) < F.size("items")).alias("repeats"),
        (F.count("record_id") - F.count_distinct("record_id")).alias("ids"),
    ).first()
    if bad.nulls or bad.repeats or bad.ids or bad.empty and on_empty_input == "error":
        raise InvalidRecords(f"{bad.nulls} with nulls, {bad.empty} empty, {bad.repeats} with repeated items, {bad.ids} repeated ids")
    return df.where(~none) if bad.empty else df
