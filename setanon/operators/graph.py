"""Connected components and pointer jumping as rounds of joins."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def reliable(df: DataFrame) -> DataFrame:
    """Cut the lineage in the folder that the cluster shares; local sessions get one of their own."""
    spark: SparkSession = df.sparkSession
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        path = spark.conf.get("spark.checkpoint.dir", None)
        if path is None:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            path = tempfile.mkdtemp(prefix="setanon-")
        sc.setCheckpointDir(path)
    return df.checkpoint()


def components(edges: DataFrame, max_rounds: int = 50) -> DataFrame:
    """(id, component_id) of nodes in ``edges(a, b)``; the least node names its component.

    Each round every node takes the least label among its neighbours and then the label of that
    label, so paths halve; a round ends with a checkpoint and one count on the driver.
    """
    both = reliable(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    label = reliable(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("l")))
    for _ in range(max_rounds):
        near = both.join(label.select(F.col("a").alias("b"), F.col("l").alias("lb")), "b").groupBy("a").agg(F.min("lb").alias("lb"))
        step = label.join(near, "a").select("a", "l", F.least("l", "lb").alias("n"))
        jump = step.join(label.select(F.col("a").alias("n"), F.col("l").alias("ln")), "n", "left").select("a", "l", F.least("n", F.coalesce("ln", "n")).alias("n"))
        jump = reliable(jump)
        if not jump.where("l <> n").head(1):
            break
        label = jump.select("a", F.col("n").alias("l"))
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return label.select(F.col("a").alias("id"), F.col("l").alias("component_id"))


def roots(parents: DataFrame, max_rounds: int = 40) -> DataFrame:
    """(node, root) of ``(node, parent)``, where roots have a null parent: each round every node
    points to its pointer's pointer."""
    at = parents.select("node", F.coalesce("parent", "node").alias("root"))
    for _ in range(max_rounds):
        nxt = reliable(at.join(at.select(F.col("node").alias("root"), F.col("root").alias("up")), "root").select("node", "root", "up"))
        if not nxt.where("root <> up").head(1):
            return nxt.select("node", F.col("up").alias("root"))
        at = nxt.select("node", F.col("up").alias("root"))
    raise RuntimeError("pointers did not settle")
