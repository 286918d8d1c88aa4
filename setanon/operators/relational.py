"""Sets as 0/1 rows, for small universes and cross-checks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def to_binary(edges: DataFrame, items: list[str] | None = None, max_items: int = 256) -> DataFrame:
    """A 0/1 column for each item. Refuses universes above ``max_items``."""
    if items is None:
        items = [r.item for r in edges.select("item").distinct().orderBy("item").limit(max_items + 1).collect()]
    if len(items) > max_items:
        raise ValueError(f"over {max_items} items: use the sparse operators")
    return edges.groupBy("record_id").pivot("item", items).agg(F.max(F.lit(1))).na.fill(0)


def from_binary(wide: DataFrame) -> DataFrame:
    items = [c for c in wide.columns if c != "record_id"]
    return wide.unpivot("record_id", [F.col(f"`{c}`") for c in items], "item", "bit").where("bit = 1").select("record_id", "item")


def majority_wide(wide: DataFrame, groups: DataFrame, tie: str = "delete") -> DataFrame:
    """Per group and column, the bit of the majority, on the 0/1 form."""
    items = [c for c in wide.columns if c != "record_id"]
    more = (lambda c: 2 * F.sum(f"`{c}`") >= F.count(F.lit(1))) if tie == "insert" else (lambda c: 2 * F.sum(f"`{c}`") > F.count(F.lit(1)))
    targets = wide.join(groups.select("record_id", "group_id"), "record_id").groupBy("group_id").agg(*(more(c).cast("int").alias(c) for c in items))
    return groups.select("record_id", "group_id").join(targets, "group_id").select("record_id", *(F.col(f"`{c}`") for c in items))


def starred_wide(starred: DataFrame, records: DataFrame) -> DataFrame:
    """Cells '0', '1' and '*' for each record of (group_id, item, state) and (record_id, group_id)."""
    items = sorted(r.item for r in starred.select("item").distinct().collect())
    cells = starred.groupBy("group_id").pivot("item", items).agg(F.first(F.when(F.col("state") == "star", "*").otherwise("1"))).na.fill("0")
    return records.select("record_id", "group_id").join(cells, "group_id").select("record_id", *(F.col(f"`{c}`") for c in items))
