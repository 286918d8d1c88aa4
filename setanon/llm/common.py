"""What the text operators share: row keys, shared-folder tables, links to components.

Rules kept by every operator here: input columns are selected by name and renamed first, so
extra or clashing columns cannot interfere; a null text is an empty text; intermediate tables
go to the folder named by ``spark.checkpoint.dir``, never to a machine's own disk.
"""

from __future__ import annotations

import tempfile
import uuid
import zlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: White space of the word contracts: \x20 and \x09-\x0D. ``bytes.split()`` splits on the same six.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share; only a local master gets a default."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not path:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        path = tempfile.mkdtemp(prefix="setanon-")
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(path)
    return path


def fresh_dir(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


#: Bytes of rows that go to a Python worker at once.
BATCH_BYTES = 4 << 20


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's bound on the bytes of an Arrow batch, which holds whole texts on both
    sides of the worker's pipe; a lower bound stays. Batch limits never change a result here."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    held = spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(name))
    if held <= 0 or held > BATCH_BYTES:
        spark.conf.set(name, str(BATCH_BYTES))


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage through a Parquet table in the shared folder; survives lost executors."""
    small_batches(df.sparkSession)
    path = fresh_dir(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Remove the files behind a table made by ``written`` once nothing reads it any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(conf).delete(path, True)


def doc_text(docs: DataFrame, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Only ``doc_id`` and non-null ``text``."""
    small_batches(docs.sparkSession)
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))


def ids_are_keys(docs: DataFrame) -> bool:
    """True if doc_id is non-null and unique (one small aggregation over that column)."""
    odd = docs.groupBy("doc_id").count().where("count > 1 OR doc_id IS NULL")
    return not odd.head(1)


def keyed(docs: DataFrame) -> DataFrame:
    """``(row_key, doc_id, text)``: the id itself when it is a key, else a number per row that is
    written down once, so that repeated rows and null ids stay separate rows."""
    slim = doc_text(docs)
    if ids_are_keys(slim):
        return slim.withColumn("row_key", F.col("doc_id"))
    return written(slim.withColumn("row_key", F.monotonically_increasing_id()), "keyed")


def release(spark: SparkSession) -> None:
    """Let the driver drop the shuffle files of finished jobs now, not at its next collection."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def key_bitmap(keys: DataFrame, bits: int = 24):
    """Bitmap of the hashes of one long column, of 2**bits bits whatever the number of keys: at
    most 2**(bits-6) words reach the driver. A prefilter; an exact join must follow."""
    import numpy as np

    slot = F.pmod(F.xxhash64(F.col(keys.columns[0])), F.lit(1 << bits))
    words = keys.select(slot.alias("s")).groupBy((F.col("s") / 64).cast("long").alias("w")).agg(F.expr("bit_or(shiftleft(1L, cast(s % 64 as int)))").alias("b")).toArrow()
    out = np.zeros(1 << (bits - 6), np.uint64)
    out[words.column("w").to_numpy()] = words.column("b").to_numpy().view(np.uint64)
    return out


def with_slot(df: DataFrame, key: str, bits: int = 24) -> DataFrame:
    """Adds ``_slot``, the place of the key in ``key_bitmap``."""
    return df.withColumn("_slot", F.pmod(F.xxhash64(key), F.lit(1 << bits)))


def only_keys(df: DataFrame, keys: DataFrame, key: str = "row_key", inside: bool = True) -> DataFrame:
    """Rows whose key is (isn't) in a bitmap of the keys; it may let a few others in."""
    import pyarrow as pa

    held = df.sparkSession.sparkContext.broadcast(key_bitmap(keys))  # of fixed size
    plain = df.columns

    def pick(batches):
        bits = held.value
        for b in batches:
            slot = b.column("_slot").to_numpy()
            hit = (bits[slot >> 6] >> (slot & 63).astype("uint64")) & 1 == 1
            yield b.select(plain).filter(pa.array(hit == inside))

    return with_slot(df, key).mapInArrow(pick, df.schema)


def with_row_key(docs: DataFrame) -> tuple[DataFrame, str]:
    """The documents, and the column that tells their rows apart: doc_id if it is a key, else a
    new one of a name that no column has, written down once."""
    if ids_are_keys(docs):
        return docs, "doc_id"
    key = "_row_key"
    while key in docs.columns:
        key += "_"
    return written(docs.withColumn(key, F.monotonically_increasing_id()), "numbered"), key


def tidy() -> None:
    """Give a worker's freed memory back to the system: workers live on after their tasks, and what
    they keep counts against their executor."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library


def crc_mod3(doc_id: Column) -> Column:
    """crc32 of the id as text, modulo 3."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 3


def unsigned_crc32(data: bytes) -> int:
    return zlib.crc32(data) & 0xFFFFFFFF


def components(edges: DataFrame, *, max_rounds: int = 60) -> DataFrame:
    """``(id, component_id)`` for every id in ``edges(a, b)``; component_id is the least member.

    Alternates the large-star and small-star steps until the edge set no longer changes; each
    round is cut in the shared folder and only a count and a checksum reach the driver.
    """
    spark = edges.sparkSession
    e = written(
        edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "edges"
    )
    seen = None
    for _ in range(max_rounds):
        # large star: every larger neighbour of a node is attached to the node's least neighbour
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = (
            both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        )
        # small star: a node and its smaller neighbours are attached to the least of them
        lower = large.groupBy("a").agg(F.min("b").alias("m"))
        small = (
            large.join(lower, "a")
            .select(F.explode(F.array(F.struct(F.col("a").alias("a"), F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("p"))
            .select("p.a", "p.b")
            .where("a <> b")
            .distinct()
        )
        nxt = written(small, "edges")
        row = nxt.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b") % 1000003).alias("s")).first()
        discard(e)
        e = nxt
        if (row.n, row.s) == seen:
            break
        seen = (row.n, row.s)
    else:
        raise RuntimeError("components did not settle")
    roots = e.select(F.col("b").alias("id")).distinct().withColumn("component_id", F.col("id"))
    return e.select(F.col("a").alias("id"), F.col("b").alias("component_id")).unionByName(roots)


def empty(spark: SparkSession, schema: str) -> DataFrame:
    return spark.createDataFrame([], T._parse_datatype_string(schema))
