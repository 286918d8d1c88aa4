"""Removal of long repeated strings by difference-cover suffix sorting.

A window is a string of ``length`` bytes inside one text. Each window names one of its own short
grams, the one of least hash, by its content alone; equal windows therefore name equal grams at
equal offsets. This synchronising sample plays the part of the difference cover between texts: it
deals all windows to buckets of one gram each, so that buckets can be sorted apart.

1. Every run of windows with one sampled position becomes a context (all their bytes). Contexts are
   named by 96 bits of hashes beside their gram's 64; a context that occurs twice is repeated whole,
   and a gram with one context ends here. What is left are the contexts around edges, one of each
   name.
2. Bucket by bucket their suffixes are sorted by the difference-cover algorithm: triples at two of
   three positions are sorted and named, the names are sorted by recursion, the remaining suffixes
   are merged in. Buckets that one task can hold are sorted there, several together; what lies in a
   gram with more than ``bucket_contexts`` contexts is sorted by all tasks together, by the same
   algorithm as a plan of range exchanges (``suffix_order``).
3. Adjacent suffixes are compared over ``length`` bytes; windows of an equal pair are repeated.
4. Repeated windows of a text are united and cut out.

Counts per name and per gram are aggregates joined back, so no task gathers what copies of one text
or users of one gram share.

Defined results: null text is an empty text; a text under ``length`` bytes keeps everything;
matches never cross texts; overlapping repeats count; repeated rows and null ids are rows of their
own; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, keyed, only_keys, release, tidy, written
from .suffix_order import repeated_windows, suffix_array
from .words import WordHasher, mix


@dataclass(frozen=True)
class Options:
    length: int = 200
    gram: int = 48
    segment: int = 1 << 18  # a longer text is sampled in overlapping parts
    bucket_contexts: int = 4_000  # contexts of a gram that one task sorts; each is under 2 * length - gram bytes
    sort_bytes: int = 1 << 18  # contexts of several grams that are sorted together
    one_task: int = 1 << 20  # symbols that end the recursion of the sort by all tasks


# ---- sorting in one task ----------------------------------------------------------------------


def repeated_starts(data: bytes, starts: np.ndarray, length: int) -> np.ndarray:
    """Which of the given window starts in ``data`` have an equal window at another given start.
    Suffixes are sorted, then neighbours compared over the window's length."""
    d = np.frombuffer(data + b"\0" * 8, np.uint8)
    order = suffix_array(d[: len(data)].astype(np.int64) + 1)
    wanted = np.zeros(len(data), bool)
    wanted[starts] = True
    order = order[wanted[order]]
    a, b = order[:-1], order[1:]
    same = np.ones(len(a), bool)
    words = np.ndarray(len(data), "<u8", d, 0, (1,)) if len(data) else np.zeros(0, "<u8")
    live = np.arange(len(a))
    for k in [*range(0, length - 8, 8), length - 8]:
        eq = words[a[live] + k] == words[b[live] + k]
        same[live[~eq]] = False
        live = live[eq]
    hit = np.zeros(len(data), bool)
    hit[a[same]] = hit[b[same]] = True
    return hit[starts]


# ---- sampling ---------------------------------------------------------------------------------

_POS = 21
_LOW = np.uint64((1 << _POS) - 1)


class Sampler:
    """Contexts of the windows of texts."""

    def __init__(self, opt: Options):
        self.opt, self.hash, self.other = opt, WordHasher(fold=False), WordHasher(fold=False, seed=1)

    @staticmethod
    def _totals(data: np.ndarray, hasher: WordHasher) -> np.ndarray:
        hasher._powers(len(data) + 1)
        total = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(hasher.values[data] * hasher.up[: len(data)], out=total[1:])
        return total

    def block(self, data: np.ndarray, size: np.ndarray):
        """For a block of texts of these sizes, under 2**21 bytes in all: gram, context name, its
        further bits, text number, first window, further windows, offset of the gram in the first window."""
        o = self.opt
        base = np.concatenate([[0], np.cumsum(size)])
        many = np.maximum(0, size - o.length + 1)
        n = int(many.sum())
        if not n:
            return [np.zeros(0, np.int64)] * 7
        total = self._totals(data, self.hash)
        grams = mix((total[o.gram :] - total[: -o.gram]) * self.hash.down[: len(data) - o.gram + 1])
        least = (grams & ~_LOW) | (_LOW - np.arange(len(grams), dtype=np.uint64))
        width, have = o.length - o.gram + 1, 1
        while have * 2 <= width:
            least = np.minimum(least[:-have], least[have:])
            have *= 2
        if have < width:
            least = np.minimum(least[: have - width], least[width - have :])
        doc = np.repeat(np.arange(len(size), dtype=np.int32), many)
        start = np.arange(n) + (base[:-1] - np.concatenate([[0], np.cumsum(many)[:-1]]))[doc]
        pick = (_LOW - (least[start] & _LOW)).astype(np.int64)
        del least
        cut = np.concatenate([[True], (pick[1:] != pick[:-1]) | (doc[1:] != doc[:-1])])
        first = np.flatnonzero(cut)
        last = np.concatenate([first[1:], [n]]) - 1
        s, e, p, doc = start[first], start[last], pick[first], doc[first]
        grams = grams[p]
        del start, pick, cut
        shape = ((p - s).astype(np.uint64) << np.uint64(32)) ^ (e - s).astype(np.uint64)
        name = mix((total[e + o.length] - total[s]) * self.hash.down[s] ^ shape)
        total = self._totals(data, self.other)
        bits = mix((total[e + o.length] - total[s]) * self.other.down[s] ^ shape) >> np.uint64(32)
        return grams.view(np.int64), name.view(np.int64), bits.astype(np.uint32).view(np.int32), doc, s - base[doc], e - s, p - s

    def texts(self, data: np.ndarray, at: np.ndarray):
        """As ``block`` for the texts that begin at ``at`` (one more entry than texts); long ones are
        cut into overlapping segments."""
        o, n, i = self.opt, len(at) - 1, 0
        while i < n:
            if at[i + 1] - at[i] > o.segment:
                for x in range(int(at[i]), int(at[i + 1]) - o.length + 1, o.segment):
                    y = min(x + o.segment + o.length - 1, int(at[i + 1]))
                    gram, name, bits, doc, s, more, back = self.block(data[x:y], np.asarray([y - x]))
                    yield gram, name, bits, doc + i, s + (x - at[i]), more, back
                i += 1
                continue
            j = max(i + 1, int(np.searchsorted(at, at[i] + o.segment, "right")) - 1)
            gram, name, bits, doc, s, more, back = self.block(data[at[i] : at[j]], np.diff(at[i : j + 1]))
            yield gram, name, bits, doc + i, s, more, back
            i = j


# ---- the operator -----------------------------------------------------------------------------


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a column of texts, one after the other, and where each begins, without a copy."""
    column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    return (np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)), at


def contexts(docs: DataFrame, opt: Options) -> DataFrame:
    """(gram, name, bits, row_key, s, more, back): windows s to s+more of a text share a sampled gram."""

    def run(batches):
        sampler = Sampler(opt)
        for b in batches:
            keys = b.column(0).to_numpy()
            for gram, name, bits, doc, s, more, back in sampler.texts(*text_bytes(b.column(1))):
                yield pa.RecordBatch.from_arrays(
                    [pa.array(gram), pa.array(name), pa.array(bits.astype(np.int32)), pa.array(keys[doc]), pa.array(s), pa.array(more.astype(np.int16)), pa.array(back.astype(np.int16))],
                    ["gram", "name", "bits", "row_key", "s", "more", "back"],
                )
            tidy()

    return docs.select("row_key", "text").mapInArrow(run, "gram long, name long, bits int, row_key long, s long, more short, back short")


NAME = ["gram", "name", "bits"]


def named(found: DataFrame) -> DataFrame:
    """(gram, name, bits, n2, names, row_key, s, more, back): for each context that occurs twice or
    shares its gram with another name, how often it occurs, its gram's names, and its first place."""
    own = found.groupBy(*NAME).agg(F.count(F.lit(1)).alias("n2"), F.min(F.struct("row_key", "s", "more", "back")).alias("lead"))
    own = written(own, "own")
    often = own.groupBy("gram").agg(F.count(F.lit(1)).alias("names"), F.sum("n2").alias("n")).where("n > 1").select("gram", "names")
    out = written(own.join(often, "gram").select(*NAME, "n2", "names", "lead.*"), "names")
    discard(own)
    release(found.sparkSession)
    return out


SPANS = "row_key long, a long, b long"


def _span_batch(rows: list[tuple[int, int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*rows) if rows else ((), (), ()))], ["row_key", "a", "b"])


def sliced(docs: DataFrame, leads: DataFrame, opt: Options) -> DataFrame:
    """(gram, row_key, s, more, alone, many, data) for each leading context."""
    lists = leads.groupBy("row_key").agg(F.collect_list(F.struct("gram", "s", "more", (F.col("n2") == 1).alias("alone"), (F.col("names") > opt.bucket_contexts).alias("many"))).alias("c"))
    both = only_keys(docs.select("row_key", "text"), leads.select("row_key")).join(lists, "row_key")

    def run(batches):
        for whole in batches:
            for first in range(0, whole.num_rows, 500):
                b = whole.slice(first, 500)
                data, at = text_bytes(b.column(1))
                for i, (key, listed) in enumerate(zip(b.column(0).to_pylist(), b.column(2))):
                    gram, s, more, alone, many = listed.values.flatten()
                    begin = (s.to_numpy() + at[i]).tolist()
                    end = (s.to_numpy() + more.to_numpy() + (at[i] + opt.length)).tolist()
                    yield pa.RecordBatch.from_arrays(
                        [gram, pa.array(np.full(len(begin), key, np.int64)), s, more, alone, many, pa.array([data[x:y].tobytes() for x, y in zip(begin, end)], pa.binary())],
                        ["gram", "row_key", "s", "more", "alone", "many", "data"],
                    )
            tidy()

    return both.mapInArrow(run, "gram long, row_key long, s long, more short, alone boolean, many boolean, data binary")


def sorted_spans(parts: DataFrame, opt: Options) -> DataFrame:
    """Spans of windows of lone contexts that occur in another context of their bucket."""

    def solve(rows):
        data = b"".join(r[4] for r in rows)
        many = np.asarray([r[2] + 1 for r in rows], np.int64)
        base = np.concatenate([[0], np.cumsum([len(r[4]) for r in rows])[:-1]])
        doc = np.repeat(np.arange(len(rows)), many)
        begin = np.arange(len(doc)) - np.concatenate([[0], np.cumsum(many)[:-1]])[doc]
        hit = repeated_starts(data, base[doc] + begin, opt.length)
        hit &= np.asarray([r[3] for r in rows])[doc]
        doc, begin = doc[hit], begin[hit]
        if not len(doc):
            return []
        cut = np.concatenate([[True], (doc[1:] != doc[:-1]) | (begin[1:] != begin[:-1] + 1)])
        first = np.flatnonzero(cut)
        last = np.concatenate([first[1:], [len(doc)]]) - 1
        return [(rows[d][0], rows[d][1] + x, rows[d][1] + y + opt.length) for d, x, y in zip(doc[first], begin[first], begin[last])]

    def run(batches):
        held, size, gram = [], 0, None
        for b in batches:
            grams, rest = b.column(0).to_pylist(), [b.column(i).to_pylist() for i in range(1, 6)]
            for g, *r in zip(grams, *rest):
                if g != gram and size >= opt.sort_bytes:
                    yield _span_batch(solve(held))
                    held, size = [], 0
                gram = g
                held.append(r)
                size += len(r[4])
        if held:
            yield _span_batch(solve(held))
        tidy()

    few = parts.where("NOT many").select("gram", "row_key", "s", "more", "alone", "data")
    return few.repartition("gram").sortWithinPartitions("gram").mapInArrow(run, SPANS)


def ranked_spans(parts: DataFrame, opt: Options) -> DataFrame:
    """The same for grams with very many contexts, whose suffixes all tasks sort together."""
    big = parts.where("many").select("row_key", "s", "alone", "data")
    if not big.head(1):
        return big.select("row_key", F.col("s").alias("a"), F.col("s").alias("b"))
    strings = written(big.withColumn("t", F.monotonically_increasing_id()), "strings")
    tasks = int(parts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    twice = repeated_windows(strings, opt.length, tasks, opt.one_task)
    out = strings.where("alone").select("t", "row_key", "s").join(twice, "t")
    return out.select("row_key", (F.col("s") + F.col("i")).alias("a"), (F.col("s") + F.col("i") + opt.length).alias("b"))


def spans(docs: DataFrame, opt: Options = Options()) -> DataFrame:
    """(row_key, a, b): byte ranges, possibly overlapping, whose union is to be removed."""
    spark = docs.sparkSession
    found = written(contexts(docs, opt), "contexts")
    names = named(found)
    leads = names.where("names > 1")
    parts = written(sliced(docs, leads, opt), "parts")
    release(spark)
    twice = names.where("n2 > 1").select(*NAME)
    whole = found.join(twice, NAME).select("row_key", F.col("s").alias("a"), (F.col("s") + F.col("more") + opt.length).alias("b"))
    out = written(whole.unionByName(sorted_spans(parts, opt)).unionByName(ranked_spans(parts, opt)), "spans")
    for table in (parts, names, found):
        discard(table)
    release(spark)
    return out


KEPT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def united(a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Maximal ranges covered by the given ones."""
    order = np.argsort(a, kind="stable")
    a, b = a[order], np.maximum.accumulate(b[order])
    new = np.concatenate([[True], a[1:] > b[:-1]])
    return list(zip(a[new].tolist(), b[np.concatenate([new[1:], [True]])].tolist()))


def cut_out(data: np.ndarray, pieces: list[tuple[int, int]]):
    """Hash of what is left."""
    left, at = hashlib.sha256(), 0
    for a, b in pieces:
        left.update(data[at:a])
        at = b
    left.update(data[at:])
    return left


def removed(docs: DataFrame, opt: Options = Options()) -> DataFrame:
    """One row per keyed document: sizes, and the hash of what is left."""
    found = spans(docs, opt)
    lists = found.groupBy("row_key").agg(F.collect_list(F.struct("a", "b")).alias("c"))

    def run(batches):
        for whole in batches:
            for first in range(0, whole.num_rows, 500):
                b = whole.slice(first, 500)
                data, at = text_bytes(b.column(1))
                rows = []
                for i, (doc_id, listed) in enumerate(zip(b.column(0).to_pylist(), b.column(2))):
                    own = data[at[i] : at[i + 1]]
                    pieces = united(listed.values.field(0).to_numpy(), listed.values.field(1).to_numpy()) if listed.is_valid else []
                    rows.append((doc_id, len(own), sum(y - x for x, y in pieces), len(pieces), cut_out(own, pieces).hexdigest()))
                cols = list(zip(*rows)) or [()] * 5
                kinds = [pa.int64()] * 4 + [pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])
            tidy()

    keys = found.select("row_key")
    slim = docs.select("row_key", "doc_id", "text")
    none = F.lit(None).cast("array<struct<a:long,b:long>>").alias("c")
    hit = only_keys(slim, keys).join(lists, "row_key", "left").select("doc_id", "text", "c")
    free = only_keys(slim, keys, inside=False).select("doc_id", "text", none)
    return hit.unionByName(free).mapInArrow(run, KEPT)


def op3_suffix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without the bytes of 200-byte strings that also start elsewhere."""
    return removed(keyed(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")))
