"""Replays of the events table through the streaming operators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import reliable
from ..operators.measures import audit
from ..plans.pipeline import AnonOptions, anonymize
from ..sources.tables import event_records, load


def replay_batches(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """Audit of all micro-batches of the events as a stream, available-now trigger. One row: the
    violations over all batches, and the records that were released or dropped."""
    schema = load(spark, sf_dir, "events").schema
    found: list[DataFrame] = []

    def each(batch: DataFrame, number: int) -> None:
        day = F.concat_ws("@", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
        recs = batch.groupBy(day.alias("record_id"), F.col("user_id").cast("string").alias("user_id")).agg(F.array_sort(F.collect_set("event_type")).alias("items"))
        r = anonymize(recs, k, AnonOptions(p=1))
        n = r.groups.select("record_id").unionByName(r.dropped.select("record_id")).agg(F.count(F.lit(1)).alias("records"))
        found.append(reliable(audit(r.records, k).select(F.col("violations").cast("long").alias("violations")).join(n)))
        r.unpersist()

    stream = spark.readStream.schema(schema).format("parquet").option("pathGlobFilter", "*.parquet").load(f"{sf_dir}/events.parquet*")
    stream.writeStream.trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out.agg(F.sum("violations").alias("violations"), F.sum("records").alias("records"))


def batch_equivalent(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """The same records released in one batch."""
    return anonymize(event_records(spark, sf_dir), k, AnonOptions(p=1)).records
