"""Pre-clustering of records by min-hash, and its alternatives."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import keyword_token, lsh_key, minhash
from ..functions.sets import is_word, jaccard
from .graph import components
from .setjoin import classes


def precluster(recs: DataFrame, p: int, fn: str = "xxhash64") -> DataFrame:
    """Adds ``bucket_id``: the concatenation of p min-hashes. p = 0 is one bucket. No shuffle."""
    key = lsh_key(F.col("items"), p, fn) if p else F.lit("all")
    return recs.withColumn("bucket_id", key)


def minhash_permutation(recs: DataFrame, seed: int) -> DataFrame:
    """The ideal form over an explicit random order of all items; for small universes, and to
    check the seeded form."""
    items = recs.select(F.explode("items").alias("item")).distinct()
    order = items.withColumn("place", F.row_number().over(W.orderBy(F.md5(F.concat(F.lit(f"order{seed}|"), "item")), "item")))
    return recs.select("record_id", F.explode("items").alias("item")).join(order, "item").groupBy("record_id").agg(F.min("place").alias("minhash"))


def bucket_sizes(bucketed: DataFrame, unit: str = "record") -> DataFrame:
    n = F.count(F.lit(1)) if unit == "record" else F.count_distinct("user_id")
    return bucketed.groupBy("bucket_id").agg(n.alias("n"))


#: Sizes of up to so many buckets are broadcast; more are joined by a shuffle of both sides.
BUCKETS = 100_000


def split_small(bucketed: DataFrame, k: int, unit: str = "record", keep_size: bool = False, counted: bool = False) -> tuple[DataFrame, DataFrame]:
    """(records of buckets that hold k units, the others). Counts are aggregated before the exchange
    and joined back, so a hot bucket can be split. ``keep_size`` leaves the count of records as
    ``_records``. ``counted`` is for records that are written down: their files are far smaller than
    their rows, and a plan by the size of files may broadcast the records, so buckets are counted first."""
    n = F.count(F.lit(1)) if unit == "record" else F.count_distinct("user_id")
    sizes = bucketed.groupBy("bucket_id").agg(n.alias("_n"), F.count(F.lit(1)).alias("_records"))
    if counted:
        sizes = F.broadcast(sizes) if sizes.limit(BUCKETS + 1).count() <= BUCKETS else sizes.hint("merge")
    n = bucketed.join(sizes, "bucket_id").select(*bucketed.columns, "_n", *(["_records"] if keep_size else []))
    return n.where(F.col("_n") >= k).drop("_n"), n.where(F.col("_n") < k).drop("_n")


def refine(bucketed: DataFrame, max_bucket: int, p: int, fn: str = "xxhash64", k: int = 1, unit: str = "record") -> DataFrame:
    """Cuts buckets above ``max_bucket`` into runs of at least that size, in the order of one more
    min-hash and then of the sets, so that like records stay together and no part falls below k.

    By user, the records of a user go where the first of them goes, and a run is made of whole
    chunks of at least k users; a run then exceeds ``max_bucket`` by less than its last chunk."""
    w = W.partitionBy("bucket_id")
    more = minhash(F.col("items"), p + 7, fn).cast("string")
    if "_records" in bucketed.columns:
        n = bucketed.withColumnRenamed("_records", "_n")
    else:
        n = bucketed.join(bucket_sizes(bucketed).withColumnRenamed("n", "_n"), "bucket_id").select(*bucketed.columns, "_n")
    big = n.where(F.col("_n") > max_bucket).withColumn("_r", F.row_number().over(w.orderBy(more, F.concat_ws("|", "items"), "record_id")))
    if unit == "record":
        part = F.least(F.floor((F.col("_r") - 1) / max_bucket), F.floor(F.col("_n") / max_bucket) - 1)
    else:
        big = big.withColumn("_first", F.min("_r").over(W.partitionBy("bucket_id", "user_id")))
        big = big.withColumn("_u", F.dense_rank().over(w.orderBy("_first")))
        chunks = F.greatest(F.floor(F.max("_u").over(w) / k), F.lit(1))  # the last takes what is over
        big = big.withColumn("_c", F.least(F.floor((F.col("_u") - 1) / k), chunks - 1))
        big = big.withColumn("_before", F.count(F.lit(1)).over(w.orderBy("_c").rangeBetween(W.unboundedPreceding, -1)))
        part = F.floor(F.col("_before") / max_bucket)
    big = big.withColumn("bucket_id", F.concat_ws("/", "bucket_id", part.cast("string"))).drop("_n", "_r", "_first", "_u", "_c", "_before")
    return n.where(F.col("_n") <= max_bucket).drop("_n").unionByName(big)


def tokenize(recs: DataFrame, hashes: int = 2, fn: str = "xxhash64", small: int = 200_000) -> tuple[DataFrame, DataFrame]:
    """(records of keyword tokens, (keyword, token)). Tokens are made once for each distinct
    keyword; an attribute item is its own token; the vocabulary is held by every task only if it has at most ``small``
    words. Other columns stay; record ids are unique, and records without items go."""
    words = recs.select(F.explode("items").alias("keyword")).distinct()
    tokens = words.select("keyword", F.when(is_word(F.col("keyword")), keyword_token(F.col("keyword"), hashes, fn)).otherwise(F.col("keyword")).alias("token"))
    if words.limit(small + 1).count() <= small:
        return _looked_up(recs.where(F.size("items") > 0), tokens), tokens
    edges = recs.select("record_id", "user_id", F.explode("items").alias("keyword")).join(tokens, "keyword")
    out = edges.groupBy("record_id", "user_id").agg(F.array_sort(F.collect_set("token")).alias("items"))
    rest = [c for c in recs.columns if c not in out.columns]
    return (out.join(recs.select("record_id", *rest), "record_id") if rest else out), tokens


def _looked_up(recs: DataFrame, tokens: DataFrame) -> DataFrame:
    """The records with the tokens of their keywords, looked up where they are: no row moves."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    held = tokens.toArrow()  # a small vocabulary
    keyword, token = held.column("keyword").combine_chunks(), held.column("token").to_pylist()
    order = sorted(set(token))
    place = {x: i for i, x in enumerate(order)}
    known = recs.sparkSession.sparkContext.broadcast((keyword, np.asarray([place[x] for x in token], np.int64), pa.array(order, pa.string())))

    def run(batches):
        keyword, code, names = known.value
        for b in batches:
            at = b.schema.get_field_index("items")
            lists = b.column(at)
            row = np.repeat(np.arange(len(lists)), lists.value_lengths().to_numpy())
            cell = np.unique(row * len(names) + code[pc.index_in(lists.flatten(), keyword).to_numpy()])
            row, own = np.divmod(cell, max(1, len(names)))
            items = pa.ListArray.from_arrays(pa.array(np.searchsorted(row, np.arange(len(lists) + 1)), pa.int32()), names.take(pa.array(own)))
            yield b.set_column(at, "items", items)

    return recs.mapInArrow(run, recs.schema)


def pairs_within(recs: DataFrame, threshold: float, bands: DataFrame | None = None) -> DataFrame:
    """(a, b, similarity) of records that share an item and reach the Jaccard threshold. Pairs come
    from an equi-join on the threshold's prefix of rarest items, never from a cross join."""
    freq = recs.select(F.explode("items").alias("item")).groupBy("item").count()
    edges = recs.select("record_id", F.size("items").alias("n"), F.explode("items").alias("item")).join(freq, "item")
    rank = F.row_number().over(W.partitionBy("record_id").orderBy("count", "item"))
    keep = F.col("n") - F.ceil(F.lit(threshold) * F.col("n") - 1e-9) + 1
    prefix = edges.withColumn("r", rank).where(F.col("r") <= keep).select("record_id", "item", "n")
    a, b = prefix.select("item", F.col("record_id").alias("a"), F.col("n").alias("na")), prefix.select("item", F.col("record_id").alias("b"), F.col("n").alias("nb"))
    ids = a.join(b, "item").where((F.col("a") < F.col("b")) & (F.least("na", "nb") >= F.lit(threshold) * F.greatest("na", "nb") - 1e-9)).select("a", "b").distinct()
    sets = recs.select("record_id", "items")
    full = ids.join(sets.select(F.col("record_id").alias("a"), F.col("items").alias("ia")), "a").join(sets.select(F.col("record_id").alias("b"), F.col("items").alias("ib")), "b")
    return full.withColumn("similarity", jaccard(F.col("ia"), F.col("ib"))).where(F.col("similarity") >= threshold - 1e-9).select("a", "b", "similarity")


#: From this similarity on, neighbours in a set's order make fewer candidates than its rarest items.
NEIGHBOURS = 0.6


def precluster_pairs(recs: DataFrame, threshold: float) -> DataFrame:
    """The all-pairs baseline: components of the graph of similar pairs."""
    if threshold >= NEIGHBOURS:
        comp = classes(recs, threshold)
    else:
        comp = components(pairs_within(recs, threshold).select("a", "b")).withColumnRenamed("id", "record_id")
    return recs.join(comp.select("record_id", "component_id"), "record_id", "left").select("record_id", "user_id", "items", F.coalesce("component_id", "record_id").alias("bucket_id"))


def precluster_bands(recs: DataFrame, p: int, bands: int, fn: str = "xxhash64") -> DataFrame:
    """Records that agree in any of several keys of p min-hashes; components over the bands."""
    keys = recs.select("record_id", F.explode(F.array(*(F.concat_ws(":", F.lit(str(b)), lsh_key(F.col("items"), p, fn, first=b * p)) for b in range(bands)))).alias("key"))
    star = keys.withColumn("hub", F.min("record_id").over(W.partitionBy("key"))).where("hub <> record_id").select(F.col("record_id").alias("a"), F.col("hub").alias("b"))
    comp = components(star)
    return recs.join(comp.select(F.col("id").alias("record_id"), "component_id"), "record_id", "left").select("record_id", "user_id", "items", F.coalesce("component_id", "record_id").alias("bucket_id"))


def precluster_mllib(recs: DataFrame, threshold: float, tables: int = 4, features: int = 1 << 18) -> DataFrame:
    """The stock alternative: MLlib's min-hash similarity join, then components."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    tf = HashingTF(inputCol="items", outputCol="v", numFeatures=features, binary=True)
    v = tf.transform(recs.where(F.size("items") > 0)).select("record_id", "v")
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=1).fit(v)
    # the join keeps distances strictly below its own threshold
    near = model.approxSimilarityJoin(v, v, 1 - threshold + 1e-6, "distance").where(F.col("distance") <= 1 - threshold + 1e-9).select(F.col("datasetA.record_id").alias("a"), F.col("datasetB.record_id").alias("b")).where("a < b")
    comp = components(near)
    return recs.join(comp.select(F.col("id").alias("record_id"), "component_id"), "record_id", "left").select("record_id", "user_id", "items", F.coalesce("component_id", "record_id").alias("bucket_id"))


