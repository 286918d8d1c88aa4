"""Records, logs and corpora derived from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sets import canonical, item_of, words

ITEM_COLUMNS = {"name": "p_name", "brand": "p_brand", "type": "p_type", "part": "l_partkey", "supp": "l_suppkey"}


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, *, fmt: str = "parquet", schema: str | None = None) -> DataFrame:
    """A table of a folder; other formats than Parquet and ORC take an explicit schema."""
    reader = spark.read.format(fmt)
    if fmt in ("csv", "json"):
        if schema is None:
            raise ValueError(f"{fmt} needs a schema")
        reader = reader.schema(schema)
    df = reader.load(f"{sf_dir}/{name}.{fmt}")
    return df.select(*columns) if columns else df


#: Parts up to this number are broadcast (two columns, some 100 MB at most); more are joined by key.
SMALL_PARTS = 2_000_000


def part_names(spark: SparkSession, sf_dir: str, column: str) -> DataFrame:
    parts = load(spark, sf_dir, "part", ["p_partkey", column])
    return F.broadcast(parts) if parts.count() <= SMALL_PARTS else parts


def line_items(spark: SparkSession, sf_dir: str, item: str = "name") -> DataFrame:
    """(order, customer-free) edges: l_orderkey and item, one row per distinct pair."""
    lines = load(spark, sf_dir, "lineitem")
    if item in ("name", "brand", "type"):
        lines = lines.join(part_names(spark, sf_dir, ITEM_COLUMNS[item]), F.col("l_partkey") == F.col("p_partkey"))
    return lines.select("l_orderkey", F.col(ITEM_COLUMNS[item]).cast("string").alias("item"))


def _grouped(edges: DataFrame, user=None) -> DataFrame:
    keys = [F.col("record_id").cast("string").alias("record_id"), (F.col("user_id") if user is None else user).cast("string").alias("user_id")]
    return edges.groupBy(*keys).agg(F.sort_array(F.collect_set("item")).alias("items"))


def market_baskets(spark: SparkSession, sf_dir: str, item: str = "name") -> DataFrame:
    """A record for each order that has lines; the user is the customer."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    e = line_items(spark, sf_dir, item).groupBy("l_orderkey").agg(F.sort_array(F.collect_set("item")).alias("items"))
    return e.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
        F.col("l_orderkey").cast("string").alias("record_id"), F.col("o_custkey").cast("string").alias("user_id"), "items"
    )


def customer_items(spark: SparkSession, sf_dir: str, item: str = "part") -> DataFrame:
    """A record for each customer: everything that the customer ever ordered."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    e = line_items(spark, sf_dir, item).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return _grouped(e.select(F.col("o_custkey").alias("record_id"), F.col("o_custkey").alias("user_id"), "item"))


def order_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A query log: user is the customer, a query each line's part name, in order of time."""
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_linenumber"]).join(part_names(spark, sf_dir, "p_name"), F.col("l_partkey") == F.col("p_partkey"))
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
        F.col("o_custkey").cast("string").alias("user_id"), F.col("o_orderdate").cast("timestamp").alias("ts"), (F.col("l_orderkey") * 100 + F.col("l_linenumber")).alias("seq"), F.col("p_name").alias("query")
    )


def conversation_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A messy log: user turns cut into sentences, one query each."""
    turns = load(spark, sf_dir, "conversations").where("role = 'user' AND text IS NOT NULL")
    return turns.select("conv_id", "turn", F.posexplode(F.split("text", r"[.!?\n]+")).alias("i", "query")).where(F.trim("query") != "").select(
        F.col("conv_id").cast("string").alias("user_id"), F.timestamp_seconds(F.col("turn")).alias("ts"), (F.col("turn") * 10000 + F.col("i")).alias("seq"), F.trim("query").alias("query")
    )


def event_records(spark: SparkSession, sf_dir: str, with_props: bool = False) -> DataFrame:
    """A record for each user and day; items are event types, with the JSON value on request."""
    e = load(spark, sf_dir, "events").withColumn("item", F.concat_ws(":", "event_type", F.get_json_object("props", "$.k")) if with_props else F.col("event_type"))
    day = F.concat_ws("@", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    return _grouped(e.select(day.alias("record_id"), "user_id", "item"))


def document_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A record for each document with a word; the user is its source."""
    d = load(spark, sf_dir, "documents", ["doc_id", "text", "source"])
    out = d.select(F.col("doc_id").cast("string").alias("record_id"), F.col("source").alias("user_id"), canonical(words(F.coalesce("text", F.lit("")))).alias("items"))
    return out.where(F.size("items") > 0)


def embedding_signs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A record for each vector: the places of its positive coordinates."""
    v = load(spark, sf_dir, "embeddings")
    places = F.filter(F.transform("embedding", lambda x, i: F.when(x > 0, F.lpad(i.cast("string"), 2, "0"))), lambda x: x.isNotNull())
    return v.select(F.col("vec_id").cast("string").alias("record_id"), F.col("label").cast("string").alias("user_id"), F.array_sort(places).alias("items")).where(F.size("items") > 0)


def customer_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quasi-identifiers of customers: nation, region, market segment."""
    n = load(spark, sf_dir, "nation").join(load(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return load(spark, sf_dir, "customer").join(n, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name", "c_mktsegment")


def profile_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = customer_profiles(spark, sf_dir)
    return p.select(F.col("c_custkey").cast("string").alias("record_id"), F.col("c_custkey").cast("string").alias("user_id"), F.array_sort(F.array(item_of("n_name", "nation"), item_of("r_name", "region"), item_of("c_mktsegment", "segment"))).alias("items"))


def corpus(spark: SparkSession, sf_dir: str, kind: str = "orders") -> DataFrame:
    """(doc, word) of a text collection for simulated result lists. Pairs may repeat: what
    reads them takes sets, which is cheaper than a shuffle of all words."""
    if kind == "orders":
        parts = part_names(spark, sf_dir, "p_name").select("p_partkey", words(F.col("p_name")).alias("w"))  # once for each part
        lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]).join(parts, F.col("l_partkey") == F.col("p_partkey"))
        return lines.select(F.col("l_orderkey").cast("long").alias("doc"), F.explode("w").alias("word"))
    table, key, text = {"documents": ("documents", "doc_id", F.col("text")), "pages": ("pages", "page_id", F.regexp_replace("html", r"(?s)<(script|style).*?</\1>|<[^>]*>", " ")), "benchmark": ("benchmark", "item_id", F.col("text")), "part": ("part", "p_partkey", F.col("p_name"))}[kind]
    return load(spark, sf_dir, table).select(F.col(key).cast("long").alias("doc"), F.explode(F.array_distinct(words(text))).alias("word"))
