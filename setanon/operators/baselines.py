"""Simple ways to release sets, to compare with. Costs are (metric, value) or edits."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import secret_id
from .majority import group_counts
from .records import to_edges


def pseudonymize(log: DataFrame, secret: str) -> DataFrame:
    """Identifiers replaced, data untouched."""
    return log.withColumn("user_id", secret_id(secret, "user_id"))


def _cost(df: DataFrame) -> DataFrame:
    return df.unpivot([], df.columns, "metric", "value").select("metric", F.col("value").cast("double").alias("value"))


def empty_all(recs: DataFrame) -> DataFrame:
    """Every item of every set deleted."""
    return _cost(recs.agg(F.lit(0).alias("add"), F.sum(F.size("items")).alias("del")))


def fill_all(recs: DataFrame) -> DataFrame:
    """Every set filled to the universe (cost only)."""
    return _cost(recs.agg(F.count(F.lit(1)).alias("n"), F.sum(F.size("items")).alias("edges")).join(recs.select(F.explode("items").alias("i")).agg(F.count_distinct("i").alias("m"))).select((F.col("n") * F.col("m") - F.col("edges")).alias("add"), F.lit(0).alias("del")))


def single_group(recs: DataFrame) -> DataFrame:
    """One group of all records, each item by its majority."""
    n = recs.agg(F.count(F.lit(1)).alias("n"))
    c = to_edges(recs).groupBy("item").count().join(n)  # a single row
    add = F.sum(F.when(2 * F.col("count") > F.col("n"), F.col("n") - F.col("count")).otherwise(0))
    gone = F.sum(F.when(2 * F.col("count") > F.col("n"), 0).otherwise(F.col("count")))
    return _cost(c.agg(add.alias("add"), gone.alias("del")))


def drop_rare(recs: DataFrame, k: int) -> DataFrame:
    """Records whose set fewer than k hold are deleted whole."""
    m = recs.groupBy("items").count().where(F.col("count") < k)
    return _cost(m.agg(F.lit(0).alias("add"), F.coalesce(F.sum(F.size("items") * F.col("count")), F.lit(0)).alias("del")))


def suppress_only(recs: DataFrame, groups: DataFrame) -> DataFrame:
    """(group_id, items, stars): the suppression solution released as it is. Items that a group does
    not share are stars for each of its records, and no majority decides them."""
    c = group_counts(recs, groups)
    same = F.col("c") == F.col("g")
    return c.groupBy("group_id").agg(F.array_sort(F.collect_list(F.when(same, F.col("item")))).alias("items"), F.sum(F.when(~same, F.col("g")).otherwise(0)).alias("stars"))


def sorted_chunks(recs: DataFrame, k: int, within: str | None = None) -> DataFrame:
    """(record_id, group_id): records in the order of their sets, cut into runs of k; the last run
    takes the rest. Without ``within`` the runs are per first item, so that no task sorts all."""
    key = F.col(within) if within else F.element_at(F.array_sort("items"), 1)
    w = W.partitionBy("_b")
    r = recs.withColumn("_b", key).withColumn("_n", F.count(F.lit(1)).over(w)).withColumn("_r", F.row_number().over(w.orderBy(F.concat_ws("|", "items"), "record_id")))
    part = F.greatest(F.lit(0), F.least(F.floor((F.col("_r") - 1) / k), F.floor(F.col("_n") / k) - 1))
    return r.select("record_id", F.concat_ws("#", "_b", part.cast("string")).alias("group_id"), F.col("_n").alias("bucket_n"))


def chunk_counts(sets: DataFrame, k: int, within: str) -> DataFrame:
    """(group_id, item, c, g) of ``sorted_chunks`` on ``weighted`` sets, without the runs that hold
    one set alone. Copies of a set follow each other, so a set takes part in at most two runs that
    others share; the buckets must hold k records."""
    w = W.partitionBy(within)
    r = sets.withColumn("_n", F.sum("weight").over(w)).withColumn("_end", F.sum("weight").over(w.orderBy(F.concat_ws("|", F.array_sort("items")), "record_id").rowsBetween(W.unboundedPreceding, 0)))
    r = r.withColumn("_last", F.greatest(F.lit(0), F.floor(F.col("_n") / k) - 1)).withColumn("_start", F.col("_end") - F.col("weight"))
    run_of = lambda place: F.least(F.floor(place / k), F.col("_last"))
    r = r.withColumn("_run", F.explode(F.array_distinct(F.array(run_of(F.col("_start")), run_of(F.col("_end") - 1)))))
    low, high = F.col("_run") * k, F.when(F.col("_run") == F.col("_last"), F.col("_n")).otherwise((F.col("_run") + 1) * k)
    r = r.withColumn("_g", high - low).withColumn("_m", F.least("_end", high) - F.greatest("_start", low)).where("_m < _g")
    cells = r.select(F.concat_ws("#", within, F.col("_run").cast("string")).alias("group_id"), F.col("_g").alias("g"), "_m", F.explode("items").alias("item"))
    return cells.groupBy("group_id", "item", "g").agg(F.sum("_m").alias("c")).select("group_id", "item", "c", "g")


def random_groups(recs: DataFrame, k: int, seed: int = 0, buckets: int = 16) -> DataFrame:
    """The sanity floor: records in hash order, cut into runs of k."""
    w = W.partitionBy("_b")
    h = F.xxhash64(F.lit(seed), "record_id")
    r = recs.withColumn("_b", F.pmod(h, F.lit(buckets))).withColumn("_n", F.count(F.lit(1)).over(w)).withColumn("_r", F.row_number().over(w.orderBy(h, "record_id")))
    part = F.greatest(F.lit(0), F.least(F.floor((F.col("_r") - 1) / k), F.floor(F.col("_n") / k) - 1))
    return r.select("record_id", F.concat_ws("#", F.col("_b").cast("string"), part.cast("string")).alias("group_id"), F.col("_n").alias("bucket_n"))


def generalize(df: DataFrame, hierarchies: list[list[str]], k: int) -> DataFrame:
    """Relational generalization with suppression: for every combination of levels, how many rows
    lie in classes under k. A hierarchy lists columns from fine to coarse; above the last is 'any'.

    All level combinations are one pass, by grouping sets."""
    import itertools

    cols = [c for h in hierarchies for c in h]
    combos = list(itertools.product(*(range(len(h) + 1) for h in hierarchies)))
    sets = []
    for combo in combos:
        sets.append([c for h, level in zip(hierarchies, combo) for c in h[level:]])
    view = f"_generalize_{abs(hash(tuple(cols))) % 10**8}"
    df.select(*cols).createOrReplaceTempView(view)
    listed = ", ".join("(" + ", ".join(s) + ")" for s in sets)
    q = f"SELECT grouping_id({', '.join(cols)}) AS gid, count(*) AS n FROM {view} GROUP BY {', '.join(cols)} GROUPING SETS ({listed})"
    by = df.sparkSession.sql(q).groupBy("gid").agg(F.count(F.lit(1)).alias("classes"), F.coalesce(F.sum(F.when(F.col("n") < k, F.col("n"))), F.lit(0)).alias("suppressed"))
    level = {}
    for combo, s in zip(combos, sets):
        gid = sum((c not in s) << (len(cols) - 1 - i) for i, c in enumerate(cols))
        level[gid] = ",".join(map(str, combo))
    names = F.create_map(*(F.lit(x) for g, v in level.items() for x in (g, v)))
    return by.select(names[F.col("gid").cast("int")].alias("levels"), "classes", "suppressed")
