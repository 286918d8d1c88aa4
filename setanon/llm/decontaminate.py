"""Benchmark decontamination by spaced seeds.

A mask keeps some of the word positions in a short stretch and ignores the rest, so a hash over
the kept words survives substitutions at the others.

1. The seeds of all benchmark items are a table; a Bloom filter of them, of bounded size, goes to the
   executors. One pass over the texts makes their seeds and keeps those that the filter admits.
2. These are joined with the benchmark's seeds by their hash. A seed that very many texts hold is
   salted, so no task gets all of them.
3. Each hit says how a text and an item lie side by side. Texts with hits meet their items, and around
   each hit the best stretch is accepted only if it is long and nearly equal; where the highest score
   is not, every other stretch is tried.

Texts without an admitted seed never move, and the size of neither table is bounded by a worker.

Defined results: null or short texts hit nothing; benchmark items with fewer words than the
shortest mask hit nothing; equal items each report; repeated rows report once for each row; of a
text and an item the stretch with the most equal words is reported, the first of equal ones; extra
columns don't interfere.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, keyed, only_keys, tidy, with_row_key, written
from .words import WordHasher, blocks, mix

#: Kept (1) and ignored (0) word positions. Fixed values.
MASKS = ("111111", "11011011", "1110010111", "11001101011")
LEAKS = "doc_id long, item_id long, word_start long, n_words long, n_equal long"


@dataclass(frozen=True)
class Options:
    min_words: int = 12  # of an accepted stretch; a shorter item must be covered by four fifths
    min_equal: float = 0.75  # share of equal words in it
    block_items: int = 2_000  # whose seeds are made together
    filter_bits: int = 28  # the seed filter has at most 2 to this power bits
    hot_seed: int = 20_000  # texts that hold a seed before it is salted
    masks: tuple[str, ...] = MASKS


def mask_hashes(words: np.ndarray, mask: str) -> np.ndarray:
    """Hash at each position where the mask fits."""
    n = len(words) - len(mask) + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.full(n, len(mask), np.uint64)
    for i, c in enumerate(mask):
        if c == "1":
            h = h * np.uint64(0x9E3779B97F4A7C15) + words[i : i + n]
    return mix(h)


class SeedIndex:
    """The form in one process, for a few items: sorted seeds with item and position."""

    def __init__(self, ids: list[int], texts: list[str], masks: tuple[str, ...]):
        self.ids, self.masks = ids, masks
        words, at = WordHasher(punctuation_is_space=True).texts([t.encode() for t in texts])
        self.words = [words[a:b] for a, b in zip(at, at[1:])]
        self.seeds = []
        for m in masks:
            hs = [mask_hashes(w, m) for w in self.words]
            h = np.concatenate(hs) if hs else np.zeros(0, np.uint64)
            item = np.repeat(np.arange(len(hs)), [len(x) for x in hs])
            pos = np.concatenate([np.arange(len(x)) for x in hs]) if hs else np.zeros(0, np.int64)
            order = np.argsort(h, kind="stable")
            self.seeds.append((h[order], item[order], pos[order]))

    def hits(self, words: np.ndarray):
        """(mask's hit position in ``words``, item, position in the item)."""
        for m, (h, item, pos) in zip(self.masks, self.seeds):
            mine = mask_hashes(words, m)
            lo, hi = np.searchsorted(h, mine, "left"), np.searchsorted(h, mine, "right")
            for at in np.flatnonzero(hi > lo).tolist():
                for j in range(lo[at], hi[at]):
                    yield at, int(item[j]), int(pos[j])


def best_stretch(equal: np.ndarray) -> tuple[int, int, int]:
    """(start, length, equal words) of the run with the largest sum of +1 and -2."""
    total = np.concatenate([[0], np.cumsum(np.where(equal, 1, -2))])
    low = np.minimum.accumulate(total)
    end = int(np.argmax(total - low))
    start = int(np.flatnonzero(total[: end + 1] == low[end])[-1])
    return start, end - start, int(equal[start:end].sum())


def accepted(equal: np.ndarray, need: float, share: float) -> tuple[int, int, int] | None:
    """As ``best_stretch`` if that is long and equal enough; else, of all the stretches that are and
    that begin and end with equal words, the first with the most equal words; None if there is none."""
    start, n, same = best_stretch(equal)
    if n >= need and same >= share * n:
        return start, n, same
    at = np.flatnonzero(equal)
    if len(at) < share * need:
        return None
    total = np.concatenate([[0.0], np.cumsum(np.where(equal, 1 - share, -share))])
    # for each last word, the earliest first word from which the share is reached
    low = np.minimum.accumulate(total[at])
    first = np.searchsorted(-low, -(total[at + 1] + 1e-9), "left")
    size, count = at + 1 - at[np.minimum(first, len(at) - 1)], np.arange(len(at)) + 1 - first
    count[size < need] = 0
    last = int(np.argmax(count))
    if count[last] <= 0:
        return None
    return int(at[first[last]]), int(size[last]), int(count[last])


def stretch(words: np.ndarray, item: np.ndarray, shifts, opt: Options) -> tuple[int, int, int] | None:
    """(start, length, equal words) of the accepted stretch with the most equal words, the first of
    equal ones, with the item laid along the text from each of the places."""
    best = None
    for shift in sorted(shifts):
        lo, hi = max(shift, 0), min(shift + len(item), len(words))
        found = accepted(words[lo:hi] == item[lo - shift : hi - shift], min(opt.min_words, 0.8 * len(item)), opt.min_equal)
        if found and (best is None or (-found[2], lo + found[0]) < (-best[2], best[0])):
            best = (lo + found[0], found[1], found[2])
    return best


def leaks_of(texts: list[bytes], hasher: WordHasher, index: SeedIndex, opt: Options):
    """(text, item, start, length, equal) over a few texts in one process."""
    for d, text in enumerate(texts):
        words, _ = hasher.texts([text])
        places: dict[int, set[int]] = {}
        for at, item, pos in index.hits(words):
            places.setdefault(item, set()).add(at - pos)
        for item in sorted(places):
            found = stretch(words, index.words[item], places[item], opt)
            if found:
                yield (d, item, *found)


# ---- the plan ---------------------------------------------------------------------------------


def items_of(benchmark: DataFrame) -> DataFrame:
    """(item, item_id, words): a number for each row of the benchmark, and its words' hashes."""

    def run(batches):
        hasher = WordHasher(punctuation_is_space=True)
        for b in batches:
            words, at = hasher.texts([t.encode() for t in b.column(2).to_pylist()])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([words[x:y].tobytes() for x, y in zip(at, at[1:])], pa.binary())], ["item", "item_id", "words"])

    rows = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return written(rows.select(F.monotonically_increasing_id().alias("item"), "item_id", "text").mapInArrow(run, "item long, item_id long, words binary"), "items")


def seeds_of(items: DataFrame, opt: Options) -> DataFrame:
    """(h, item, pos) of every place where a mask fits."""

    def run(batches):
        for whole in batches:
            for first in range(0, whole.num_rows, opt.block_items):
                b = whole.slice(first, opt.block_items)
                for item, words in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                    words = np.frombuffer(words, np.uint64)
                    hs = [mask_hashes(words, m) for m in opt.masks]
                    n = sum(map(len, hs))
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(hs).view(np.int64)), pa.array(np.full(n, item)), pa.array(np.concatenate([np.arange(len(h), dtype=np.int32) for h in hs]))], ["h", "item", "pos"])

    return items.select("item", "words").mapInArrow(run, "h long, item long, pos int")


def seed_filter(seeds: DataFrame, opt: Options) -> tuple[np.ndarray, int]:
    """Bloom filter of two places for each seed, and its size as a power of two: 64 bits for each seed,
    within the bound. Past it more seeds of texts are admitted, and the join still decides."""
    n = seeds.count()
    power = min(opt.filter_bits, max(16, int(64 * n).bit_length()))
    low = F.lit((1 << power) - 1)
    places = seeds.select(F.explode(F.array(F.col("h").bitwiseAND(low), F.shiftrightunsigned("h", 32).bitwiseAND(low))).alias("s"))
    words = places.groupBy(F.shiftright("s", 6).alias("w")).agg(F.expr("bit_or(shiftleft(1L, cast(s & 63 as int)))").alias("b")).toArrow()
    bits = np.zeros(1 << (power - 6), np.uint64)
    bits[words.column("w").to_numpy()] = words.column("b").to_numpy().view(np.uint64)
    return bits, power


def admitted(h: np.ndarray, bits: np.ndarray, power: int) -> np.ndarray:
    """Positions of the hashes that the filter lets in."""
    low, out = np.uint64((1 << power) - 1), np.arange(len(h))
    for shift in (0, 32):
        s = (h[out] >> np.uint64(shift)) & low
        out = out[(bits[(s >> np.uint64(6)).astype(np.int64)] >> (s & np.uint64(63))) & np.uint64(1) == 1]
    return out


def text_seeds(docs: DataFrame, seeds: DataFrame, opt: Options) -> DataFrame:
    """(h, row_key, at) of the texts' seeds that the filter admits."""
    held = docs.sparkSession.sparkContext.broadcast(seed_filter(seeds, opt))  # of bounded size

    def run(batches):
        bits, power = held.value
        hasher = WordHasher(punctuation_is_space=True)
        for b in batches:
            keys, first = b.column(0).to_numpy(), 0
            for block in blocks([t.encode() for t in b.column(1).to_pylist()], 1 << 20):
                words, bounds = hasher.texts(block)
                for m in opt.masks:
                    h = mask_hashes(words, m)
                    at = admitted(h, bits, power)
                    doc = np.searchsorted(bounds, at, "right") - 1
                    inside = at + len(m) <= bounds[doc + 1]
                    at, doc = at[inside], doc[inside]
                    if len(at):
                        yield pa.RecordBatch.from_arrays([pa.array(h[at].view(np.int64)), pa.array(keys[first + doc]), pa.array((at - bounds[doc]).astype(np.int32))], ["h", "row_key", "at"])
                first += len(block)
        tidy()

    return docs.select("row_key", "text").mapInArrow(run, "h long, row_key long, at int")


def salted(mine: DataFrame, seeds: DataFrame, opt: Options) -> tuple[DataFrame, DataFrame]:
    """Both sides with a ``salt``: the texts that hold a hot seed are dealt over several, and the
    benchmark's rows of that seed are repeated for each."""
    hot = mine.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > opt.hot_seed)
    hot = written(hot.select("h", F.ceil(F.col("n") / opt.hot_seed).cast("int").alias("salts")), "hot")
    small = hot.limit(1_000_001).count() <= 1_000_000  # 16 bytes each
    side = F.broadcast(hot) if small else hot
    one: Column = F.coalesce("salts", F.lit(1))
    dealt = mine.join(side, "h", "left").select("h", "row_key", "at", F.pmod(F.xxhash64("row_key"), one).cast("int").alias("salt"))
    spread = seeds.join(side, "h", "left").select("h", "item", "pos", F.explode(F.sequence(F.lit(0), one - 1)).alias("salt"))
    return dealt, spread


def row_leaks(docs: DataFrame, benchmark: DataFrame, opt: Options) -> DataFrame:
    """(row_key, doc_id, item_id, word_start, n_words, n_equal) for keyed documents, written down."""
    items = items_of(benchmark)
    seeds = written(seeds_of(items, opt), "seeds")
    mine = written(text_seeds(docs, seeds, opt), "admitted")
    dealt, spread = salted(mine, seeds, opt)
    places = dealt.join(spread, ["h", "salt"]).groupBy("row_key", "item").agg(F.collect_set(F.col("at") - F.col("pos")).alias("shifts"))
    places = written(places, "places")
    lists = places.join(items, "item").groupBy("row_key").agg(F.collect_list(F.struct("item_id", "words", "shifts")).alias("c"))
    both = only_keys(docs.select("row_key", "doc_id", "text"), places.select("row_key")).join(lists, "row_key")
    schema = pa.schema([(c.split()[0], pa.int64()) for c in f"row_key long, {LEAKS}".split(", ")])

    def run(batches):
        hasher = WordHasher(punctuation_is_space=True)
        for whole in batches:
            for first in range(0, whole.num_rows, 200):
                out = []
                for key, doc_id, text, listed in zip(*(whole.slice(first, 200).column(k).to_pylist() for k in range(4))):
                    words, _ = hasher.texts([text.encode()])
                    for x in listed:
                        found = stretch(words, np.frombuffer(x["words"], np.uint64), x["shifts"], opt)
                        if found:
                            out.append((key, doc_id, x["item_id"], *found))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out)], schema=schema)
        tidy()

    found = written(both.mapInArrow(run, f"row_key long, {LEAKS}"), "leaks")
    for table in (items, seeds, mine, places):
        discard(table)
    return found


def leaks(docs: DataFrame, benchmark: DataFrame, opt: Options = Options()) -> DataFrame:
    """One row for each document and benchmark item of which it holds a stretch."""
    return row_leaks(keyed(docs), benchmark, opt).drop("row_key")


def clean(docs: DataFrame, benchmark: DataFrame, opt: Options = Options()) -> DataFrame:
    """The documents, columns as they came, that hold no stretch of any item."""
    base, key = with_row_key(docs)
    slim = base.select(F.col(key).cast("long").alias("row_key"), F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    bad = row_leaks(slim, benchmark, opt).select(F.col("row_key").alias(key)).distinct()
    return base.join(bad, key, "left_anti").select(*docs.columns)


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every leak of ``benchmark`` into ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text"))
