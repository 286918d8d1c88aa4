"""Writers for released tables."""

from __future__ import annotations

from pyspark.sql import DataFrame


def release(df: DataFrame, path: str, *, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    """Write a released table; ``partition_by`` columns become folders that readers prune by."""
    w = df.write.mode(mode).format(fmt)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def release_table(df: DataFrame, name: str, key: str, buckets: int, *, mode: str = "overwrite") -> None:
    """A bucketed, sorted table, so that later joins on the key move nothing."""
    df.write.mode(mode).bucketBy(buckets, key).sortBy(key).saveAsTable(name)
