"""Cost, privacy and structure measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.sets import hamming
from .clustering import medoid
from .majority import group_counts
from .records import to_edges, weight_of


def edit_cost(edits: DataFrame) -> DataFrame:
    """(op, n)."""
    return edits.groupBy("op").agg(F.count(F.lit(1)).alias("n"))


def cost_profile(cost: DataFrame, n_records, n_edges) -> DataFrame:
    """Ratios of a cost table: share of insertions, edits per record, share of edges changed."""
    c = cost.groupBy().pivot("metric", ["add", "del_in_group", "del_small_cluster", "total"]).agg(F.first("value"))
    return c.select(
        (F.col("add") / F.greatest(F.col("total"), F.lit(1.0))).alias("add_share"),
        (F.col("total") / F.lit(float(n_records))).alias("per_record"),
        (F.col("total") / F.lit(float(n_edges))).alias("edge_share"),
    )


def audit(recs: DataFrame, k: int, unit: str = "record") -> DataFrame:
    """One row: least multiplicity of a set and records whose set fewer than k units hold."""
    n = F.count(F.lit(1)) if unit == "record" else F.count_distinct("user_id")
    m = recs.groupBy(F.array_sort("items").alias("items")).agg(n.alias("n"), F.count(F.lit(1)).alias("records"))
    return m.agg(F.coalesce(F.min("n"), F.lit(0)).alias("least"), F.coalesce(F.sum(F.when(F.col("n") < k, F.col("records"))), F.lit(0)).alias("violations"), F.count(F.lit(1)).alias("sets"))


def uniqueness(recs: DataFrame, k: int) -> DataFrame:
    """One row: records, those alone with their set, those in sets of fewer than k."""
    m = recs.groupBy("items").agg(F.count(F.lit(1)).alias("n"))
    s = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0))
    return m.agg(F.sum("n").alias("records"), s(F.col("n") == 1).alias("unique_records"), s(F.col("n") < k).alias("below_k"))


def lower_bound(recs: DataFrame, k: int, within: str) -> DataFrame:
    """(bucket, bound): no grouping inside the bucket costs less than half the sum, over records,
    of the mean distance to their k-1 nearest others. Records may be ``weighted``.

    Copies are each other's nearest, so pairs are made of different sets only, and only for sets
    that fewer than k records hold; a pair's distances are counted before they are put in order."""
    sets = recs.groupBy(within, "items").agg(F.sum(weight_of(recs)).alias("w"))
    few = sets.where(F.col("w") < k).select(within, F.col("items").alias("ia"), F.col("w").alias("wa"))
    others = sets.select(within, F.col("items").alias("ib"), F.col("w").alias("wb"))
    pairs = few.join(others, within).where(F.col("ia") != F.col("ib")).select(within, "ia", "wa", "wb", hamming(F.col("ia"), F.col("ib")).alias("d"))
    far = pairs.groupBy(within, "ia", "wa", "d").agg(F.sum("wb").alias("n")).groupBy(within, "ia", "wa").agg(F.array_sort(F.collect_list(F.struct("d", "n"))).alias("r"))
    left, total = F.lit(k).cast("long") - F.col("wa"), F.lit(0).cast("long")  # seats beside the copies
    take = lambda acc, x: F.least(acc["left"], x["n"])
    spent = F.aggregate("r", F.struct(left.alias("left"), total.alias("d")), lambda acc, x: F.struct((acc["left"] - take(acc, x)).alias("left"), (acc["d"] + take(acc, x) * x["d"]).alias("d")))
    sums = far.select(within, (F.col("wa") * spent["d"] / (k - 1)).alias("mean")).groupBy(within).agg(F.sum("mean").alias("mean"))
    whole = sets.groupBy(within).agg(F.sum("w").alias("w")).where("w > 1")
    return whole.join(sums, within, "left").select(within, (F.coalesce("mean", F.lit(0.0)) / 2).alias("bound"))


def ratio_to_bound(cost: DataFrame, bound: DataFrame, within: str) -> DataFrame:
    """One row of ``cost(bucket, cost)`` over ``bound(bucket, bound)``: buckets, total cost, total
    bound, and their ratio, which no solution's true ratio to the optimum exceeds."""
    j = cost.join(bound, within)
    total = j.agg(F.count(F.lit(1)).alias("buckets"), F.coalesce(F.sum("cost"), F.lit(0)).cast("double").alias("cost"), F.round(F.coalesce(F.sum("bound"), F.lit(0.0)), 4).alias("bound"))
    return total.withColumn("ratio", F.round(F.col("cost") / F.greatest("bound", F.lit(1e-9)), 4))


def ratio_exact(recs: DataFrame, k: int, within: str = "bucket_id", max_n: int = 10, objective: str = "flip") -> DataFrame:
    """(bucket, n, best): optimal cost of every bucket of k to max_n records, by exhaustive search."""
    import pyarrow as pa

    from .kernel import Bucket, exact_groups

    w = W.partitionBy(within)
    small = recs.select("record_id", "user_id", "items", F.col(within).alias("bucket_id")).withColumn("_n", F.count(F.lit(1)).over(W.partitionBy("bucket_id"))).where((F.col("_n") >= k) & (F.col("_n") <= max_n)).drop("_n")
    del w

    def run(table):
        ids, users, sets = (table.column(c).to_pylist() for c in ("record_id", "user_id", "items"))
        best, _ = exact_groups(Bucket(ids, users, [frozenset(s) for s in sets]).m, k, objective)
        return pa.table({"bucket_id": pa.array([table.column("bucket_id")[0].as_py()], pa.string()), "n": pa.array([len(ids)], pa.int64()), "best": pa.array([best], pa.float64())})

    return small.groupBy("bucket_id").applyInArrow(run, "bucket_id string, n long, best double")


def check_factors(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """One row of violations over groups: twice the flips above the stars, the majority above the
    medoid, the medoid above the random expectation, that above twice the majority."""
    c, g = F.col("c"), F.col("g")
    j = group_counts(recs, groups).groupBy("group_id").agg(F.sum(F.least(c, g - c)).alias("flips"), F.sum(F.when(c < g, g).otherwise(0)).alias("stars"), F.sum(2 * c * (g - c) / g).alias("expected"))
    j = j.join(medoid(recs, groups).select("group_id", "cost"), "group_id")
    eps = F.lit(1e-9)
    return j.agg(
        F.count(F.lit(1)).alias("groups"),
        F.count_if(2 * F.col("flips") > F.col("stars")).alias("flips_over_half_stars"),
        F.count_if(F.col("flips") > F.col("cost")).alias("majority_over_medoid"),
        F.count_if(F.col("cost") > F.col("expected") + eps).alias("medoid_over_random"),
        F.count_if(F.col("expected") > 2 * F.col("flips") + eps).alias("random_over_twice"),
    )


def thread_stats(threads: DataFrame) -> DataFrame:
    """One row for thread sets: users, queries, threads, mean unique keywords."""
    return threads.agg(F.count_distinct("user_id").alias("users"), F.sum(F.size("queries")).alias("queries"), F.count(F.lit(1)).alias("threads"), F.round(F.avg(F.size("items")), 6).alias("avg_keywords"))


def cluster_stats(bucketed: DataFrame) -> DataFrame:
    """One row: clusters, mean and largest size, and the most common item of the largest."""
    n = bucketed.groupBy("bucket_id").agg(F.count(F.lit(1)).alias("n"))
    top = n.agg(F.count(F.lit(1)).alias("clusters"), F.round(F.avg("n"), 6).alias("avg_size"), F.max("n").alias("largest"), F.max_by("bucket_id", F.struct("n", "bucket_id")).alias("bucket_id"))
    item = bucketed.join(top.select("bucket_id"), "bucket_id").select(F.explode("items").alias("item")).groupBy("item").count().agg(F.max_by("item", F.struct("count", "item")).alias("top_item"))
    return top.drop("bucket_id").join(item)  # two single rows


def size_histogram(bucketed: DataFrame) -> DataFrame:
    return bucketed.groupBy("bucket_id").agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("clusters"))


def collision_calibration(pairs: DataFrame, p: int, trials: int) -> DataFrame:
    """Of pairs (ia, ib): mean similarity, its p-th power, and the observed rate at which p
    concatenated min-hashes agree over the trials."""
    from ..functions.hashing import minhash
    from ..functions.sets import jaccard

    agree = F.lit(0)
    for t in range(trials):
        same = F.lit(True)
        for i in range(p):
            same = same & (minhash(F.col("ia"), t * p + i) == minhash(F.col("ib"), t * p + i))
        agree = agree + same.cast("int")
    j = jaccard(F.col("ia"), F.col("ib"))
    return pairs.agg(F.avg(j).alias("similarity"), F.avg(F.pow(j, F.lit(p))).alias("expected"), F.avg(agree / trials).alias("observed"))


def small_cluster_cost(dropped: DataFrame) -> DataFrame:
    return dropped.agg(F.count(F.lit(1)).alias("records"), F.coalesce(F.sum("n_items"), F.lit(0)).alias("items"))


def placement_loss(before: DataFrame, after: DataFrame) -> DataFrame:
    """Share of inserted keywords that stand next to a word they never neighbour in the original
    queries. Both are (query)."""
    from ..functions.sets import words

    def bigrams(df, col):
        w = words(F.col(col))
        return df.select(F.explode(F.transform(F.slice(w, 1, F.greatest(F.size(w) - 1, F.lit(0))), lambda x, i: F.struct(x.alias("x"), F.get(w, i + 1).alias("y")))).alias("p")).select("p.x", "p.y")

    known = bigrams(before, "query").distinct().withColumn("known", F.lit(1))
    fresh = after.where(F.size("inserted") > 0).select("after", F.explode("inserted").alias("y0"))
    pairs = bigrams(fresh.withColumnRenamed("after", "query").withColumn("k", F.col("y0")), "query").join(fresh.select(F.col("y0").alias("y")).distinct(), "y")
    j = pairs.join(known, ["x", "y"], "left")
    return j.agg(F.count(F.lit(1)).alias("placed"), F.round(F.coalesce(F.avg(F.when(F.col("known").isNull(), 1.0).otherwise(0.0)), F.lit(0.0)), 6).alias("loss"))


def itemset_pairs(recs: DataFrame, support: int) -> DataFrame:
    """(x, y, n): frequent pairs of items; infrequent items go before the self-join."""
    e = to_edges(recs)
    often = e.groupBy("item").count().where(F.col("count") >= support).select("item")
    kept = e.join(often, "item")
    a, b = kept.select("record_id", F.col("item").alias("x")), kept.select("record_id", F.col("item").alias("y"))
    return a.join(b, "record_id").where("x < y").groupBy("x", "y").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= support)
