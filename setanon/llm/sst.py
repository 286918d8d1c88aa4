"""Sorted-string-table shards of token ids.

File: blocks, then a sparse index (one entry per block), a Bloom filter over keys, and a footer
of fixed size. In a block, keys are prefix-compressed between restart points. Lookup: Bloom
filter, binary search in the index, binary search among restarts, short scan.

Defined results: null text is an empty text (its ids are the end id alone); a null doc_id sorts
first; rows that repeat a doc_id are all kept, ordered by text; an empty table gives no shard.
Shard writes are idempotent: a retried task writes the same bytes to a scratch name and moves
them over, so a lost executor costs only its own shards.
"""

from __future__ import annotations

import bisect
import struct
import uuid
import zlib

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import doc_text, fresh_dir
from .encoding import encoder

MAGIC = b"STNSST01"
FOOTER = struct.Struct("<QQQQQQ8s")  # index at, size; bloom at, size; entries; id bytes; magic
RESTART = 16


def key_of(doc_id: int | None) -> bytes:
    """Order-preserving key: a null sorts before every number."""
    return b"\x00" if doc_id is None else b"\x01" + struct.pack(">Q", (doc_id + (1 << 63)) & (2**64 - 1))


def id_of(key: bytes) -> int | None:
    return None if key == b"\x00" else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(buf, at: int) -> tuple[int, int]:
    shift = n = 0
    while True:
        b = buf[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def _bloom_bits(key: bytes, m: int, k: int):
    a, b = zlib.crc32(key), zlib.adler32(key[::-1]) * 2654435761 % 2**32 | 1
    return ((a + i * b) % m for i in range(k))


class Writer:
    """Streams sorted (key, value) pairs into a file object; holds one block and the keys' hashes."""

    def __init__(self, out, *, id_bytes: int, block_bytes: int = 64 << 10, bits_per_key: int = 10):
        self.out, self.id_bytes, self.block_bytes, self.bits = out, id_bytes, block_bytes, bits_per_key
        self.at, self.n, self.index, self.keys = 0, 0, [], []
        self.zip = zstandard.ZstdCompressor(level=1)
        self._new()

    def _new(self):
        self.block, self.restarts, self.count, self.last = bytearray(), [], 0, b""

    def add(self, key: bytes, value: bytes) -> None:
        if self.count % RESTART == 0:
            self.restarts.append(len(self.block))
            shared = 0
        else:
            shared = 0
            for x, y in zip(self.last, key):
                if x != y:
                    break
                shared += 1
        self.block += _varint(shared) + _varint(len(key) - shared) + _varint(len(value)) + key[shared:] + value
        self.last, self.count, self.n = key, self.count + 1, self.n + 1
        self.keys.append(key)
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _flush(self) -> None:
        if not self.count:
            return
        raw = bytes(self.block) + struct.pack(f"<{len(self.restarts)}II", *self.restarts, len(self.restarts))
        data = self.zip.compress(raw)
        self.out.write(data + struct.pack("<I", zlib.crc32(data)))
        self.index.append((self.last, self.at, len(data)))
        self.at += len(data) + 4
        self._new()

    def close(self) -> None:
        self._flush()
        index = bytearray()
        for key, at, size in self.index:
            index += _varint(len(key)) + key + _varint(at) + _varint(size)
        m = max(64, self.bits * self.n)
        bloom = bytearray(m // 8 + 1)
        for key in self.keys:
            for b in _bloom_bits(key, m, 7):
                bloom[b >> 3] |= 1 << (b & 7)
        bloom = struct.pack("<Q", m) + bloom
        self.out.write(bytes(index))
        self.out.write(bytes(bloom))
        self.out.write(FOOTER.pack(self.at, len(index), self.at + len(index), len(bloom), self.n, self.id_bytes, MAGIC))


class Reader:
    """Random access and scans over one shard; ``source`` has read/seek/size."""

    def __init__(self, source):
        self.f = source
        source.seek(0, 2)
        end = source.tell()
        source.seek(end - FOOTER.size)
        at, size, bat, bsize, self.n, self.id_bytes, magic = FOOTER.unpack(source.read(FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a shard")
        buf, i, self.last, self.where = self._at(at, size), 0, [], []
        while i < len(buf):
            n, i = _read_varint(buf, i)
            self.last.append(bytes(buf[i : i + n]))
            a, i = _read_varint(buf, i + n)
            s, i = _read_varint(buf, i)
            self.where.append((a, s))
        self._bloom_at = (bat, bsize)
        self._bloom = None
        self.unzip = zstandard.ZstdDecompressor()

    def _at(self, at: int, size: int) -> bytes:
        self.f.seek(at)
        return self.f.read(size)

    def _block(self, i: int):
        at, size = self.where[i]
        data = self._at(at, size + 4)
        if zlib.crc32(data[:-4]) != struct.unpack("<I", data[-4:])[0]:
            raise ValueError("a block is damaged")
        raw = self.unzip.decompress(data[:-4])
        n = struct.unpack("<I", raw[-4:])[0]
        return raw, struct.unpack(f"<{n}I", raw[-4 * n - 4 : -4]), len(raw) - 4 * n - 4

    @staticmethod
    def _entries(raw, at: int, end: int):
        key = b""
        while at < end:
            shared, at = _read_varint(raw, at)
            own, at = _read_varint(raw, at)
            size, at = _read_varint(raw, at)
            key = key[:shared] + raw[at : at + own]
            at += own
            yield key, raw[at : at + size]
            at += size

    def scan(self):
        for i in range(len(self.where)):
            raw, _, end = self._block(i)
            yield from self._entries(raw, 0, end)

    def may_have(self, key: bytes) -> bool:
        if self._bloom is None:
            raw = self._at(*self._bloom_at)
            self._bloom = struct.unpack("<Q", raw[:8])[0], raw[8:]
        m, bits = self._bloom
        return all(bits[b >> 3] >> (b & 7) & 1 for b in _bloom_bits(key, m, 7))

    def get(self, doc_id: int | None) -> np.ndarray | None:
        """Ids of the first entry with that key, or None."""
        key = key_of(doc_id)
        if not self.may_have(key):
            return None
        i = bisect.bisect_left(self.last, key)
        if i == len(self.last):
            return None
        raw, restarts, end = self._block(i)
        lo, hi = 0, len(restarts) - 1
        while lo < hi:
            mid = (lo + hi + 1) // 2
            if next(self._entries(raw, restarts[mid], end))[0] < key:
                lo = mid
            else:
                hi = mid - 1
        for k, v in self._entries(raw, restarts[lo], end):
            if k == key:
                return np.frombuffer(v, dtype=f"<u{self.id_bytes}")
            if k > key:
                return None
        return None


def _filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


def open_shard(uri: str) -> Reader:
    store, path = _filesystem(uri)
    return Reader(store.open_input_file(path))


MANIFEST = "shard string, path string, first_id long, last_id long, n_docs long, n_tokens long"


def write_shards(docs: DataFrame, out: str, *, tokenizer: str, end_id: int = 0, vocab: int = 50_257) -> DataFrame:
    """Encode, append ``end_id``, write shards in ascending doc_id order under ``out`` (any store
    that Arrow's file systems reach). Returns the manifest, one row per shard."""
    id_bytes = 2 if vocab <= 65_536 else 4

    def run(batches):
        enc, writer, sink, made = encoder(tokenizer, True), None, None, {}
        store, folder = _filesystem(out)
        name = f"shard-{TaskContext.get().partitionId():06d}.sst"
        scratch = f"{folder}/.{name}.{uuid.uuid4().hex}"
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            flat, sizes = enc.closed(texts, end_id)
            flat, at = memoryview(flat.astype(f"<u{id_bytes}")).cast("B"), 0
            for doc_id, size in zip(ids, (sizes * id_bytes).tolist()):
                if writer is None:
                    store.create_dir(folder, recursive=True)
                    sink = store.open_output_stream(scratch)
                    writer = Writer(sink, id_bytes=id_bytes)
                    made = {"first_id": doc_id, "n_tokens": 0}
                value = bytes(flat[at : at + size])
                at += size
                writer.add(key_of(doc_id), value)
                made["last_id"] = doc_id
                made["n_tokens"] += len(value) // id_bytes
        if writer is not None:
            writer.close()
            sink.close()
            store.move(scratch, f"{folder}/{name}")
            yield pa.RecordBatch.from_pylist(
                [made | {"shard": name, "path": f"{out}/{name}", "n_docs": writer.n}],
                schema=pa.schema([("shard", pa.string()), ("path", pa.string()), ("first_id", pa.int64()), ("last_id", pa.int64()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]),
            )

    spread = doc_text(docs).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return spread.mapInArrow(run, MANIFEST)


READ = "doc_id long, start long, n_tokens long, ids_crc32 long, shard string"


def read_shards(spark: SparkSession, manifest: DataFrame) -> DataFrame:
    """One row per document from the files. The manifest has a row per shard, so the running
    start of each shard is summed on the driver."""
    start, rows = 0, []
    for r in sorted(manifest.collect(), key=lambda r: r.shard):
        rows.append((r.shard, r.path, start))
        start += r.n_tokens
    work = spark.createDataFrame(rows, "shard string, path string, start long").repartition(max(1, len(rows)))

    def run(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64()), ("shard", pa.string())])
        for batch in batches:
            for row in batch.to_pylist():
                reader, at, held = open_shard(row["path"]), row["start"], []
                for key, value in reader.scan():
                    ids = np.frombuffer(value, dtype=f"<u{reader.id_bytes}").astype("<u4")
                    held.append((id_of(key), at, len(ids), zlib.crc32(ids.tobytes()), row["shard"]))
                    at += len(ids)
                    if len(held) >= 5000:
                        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held), schema)], schema=schema)
                        held = []
                if held:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held), schema)], schema=schema)

    return work.mapInArrow(run, READ)


def op2_sst(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token ids of every document through written shards: doc_id, start, n_tokens, ids_crc32, shard."""
    import public_tokenizers

    from .common import discard, written

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    made = written(write_shards(docs, fresh_dir(spark, "sst"), tokenizer=public_tokenizers.path("byte_bpe_50k.json")), "manifest")
    out = read_shards(spark, made)
    discard(made)
    return out
