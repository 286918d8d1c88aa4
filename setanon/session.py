"""Sessions for local runs; on a cluster the same settings belong to the submission."""

from __future__ import annotations

from pyspark.sql import SparkSession

SETTINGS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    "spark.ui.enabled": "false",
}


def local_session(cpus: int = 8, *, partitions: int = 8, memory: str = "8g") -> SparkSession:
    b = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", partitions).config("spark.driver.memory", memory)
    s = b.config(map=SETTINGS).config("spark.driver.host", "127.0.0.1").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    return s
