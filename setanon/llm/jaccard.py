"""Exact similarity join on word shingles, and the classes that its links form.

Shingles get one global order, rare ones first: those that are frequent in a first count of
hash-ordered prefixes come last, by frequency. Only a short prefix of each set is joined; length
and positional filters drop pairs before a text is read, the suffix filter before sets are
intersected, and each pair is verified once on whole sets.

Equal sets are one node from the start. A shingle that many sets share would pair them all, so in
a long posting every set is compared with one hub only, the one in most long postings. Sets of one
class by then need nothing more. For sets x and y still apart, what they share lies partly in the
hub H, and that part is at most min(|x & H|, |y & H|). If this alone could reach the overlap that a
link needs, the pair is compared; else x and y must share a shingle outside H, which a second
prefix join, over x - H and y - H, finds. So no link between classes is lost, and the pairs that
merely resemble the same hub are never made.

Defined results: a null or blank text has an empty set and links with nothing; with fewer words
than a shingle the whole sequence is the shingle; repeated rows and null ids are separate rows; a
null id never names a class that has another id.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import components, discard, keyed, only_keys, release, tidy, with_row_key, written
from .words import WordHasher, blocks, windows


@dataclass(frozen=True)
class Options:
    words: int = 5
    num: int = 80  # two sets link when den * intersection >= num * union
    den: int = 100
    short_posting: int = 8  # a shingle in so few sets pairs them all at once
    frequent: int = 8  # prefixes that hold a shingle before it counts as frequent
    max_frequent: int = 500_000  # shingles held by every worker; frequent doubles until they fit


def overlap_needed(nx, ny, opt: Options):
    """Least intersection of linked sets of these sizes."""
    return -(-opt.num * (nx + ny) // (opt.num + opt.den))


def prefix_length(n, opt: Options):
    return n - (opt.num * n + opt.den - 1) // opt.den + 1


_HASHER = WordHasher()


def _rest() -> None:
    """A worker that has ended a task keeps nothing that grew in it."""
    _HASHER.rest()
    tidy()


def shingle_sets(texts: list[str], opt: Options):
    """The sorted distinct shingle hashes of each text."""
    out = []
    for block in blocks([t.encode() for t in texts]):
        h, at = windows(*_HASHER.texts(block), opt.words)
        out += [np.unique(h[a:b]) for a, b in zip(at, at[1:])]
    return out


class Order:
    """Rare first: shingles that are not frequent by hash, then frequent ones by count."""

    def __init__(self, frequent: np.ndarray, counts: np.ndarray):
        order = np.argsort(frequent, kind="stable")
        self.frequent, self.counts = frequent[order], counts[order]

    def __call__(self, s: np.ndarray) -> np.ndarray:
        if not len(self.frequent) or not len(s):
            return s
        i = np.minimum(np.searchsorted(self.frequent, s), len(self.frequent) - 1)
        hot = self.frequent[i] == s
        if not hot.any():
            return s
        tail, c = s[hot], self.counts[i[hot]]
        return np.concatenate([s[~hot], tail[np.lexsort((tail, c))]])


NONE = Order(np.zeros(0, np.uint64), np.zeros(0, np.int64))


def node_of(s: np.ndarray) -> tuple[int, int]:
    """Two 64-bit names of a set."""
    d = hashlib.blake2b(s.tobytes(), digest_size=16).digest()
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def described(docs: DataFrame, opt: Options) -> DataFrame:
    """(row_key, doc_id, n, node, mark): set size and names of each row."""

    def run(batches):
        for b in batches:
            sets = shingle_sets(b.column("text").to_pylist(), opt)
            names = [node_of(s) for s in sets]
            yield pa.RecordBatch.from_arrays(
                [b.column("row_key"), b.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array([x for x, _ in names], pa.int64()), pa.array([y for _, y in names], pa.int64())],
                ["row_key", "doc_id", "n", "node", "mark"],
            )
        _rest()

    return docs.select("row_key", "doc_id", "text").mapInArrow(run, "row_key long, doc_id long, n long, node long, mark long")


def _frequent(docs: DataFrame, opt: Options) -> Order:
    """Shingles in many hash-ordered prefixes, counted over all texts."""

    def run(batches):
        for b in batches:
            sets = shingle_sets(b.column(0).to_pylist(), opt)
            h = np.concatenate([s[: prefix_length(len(s), opt)] for s in sets if len(s)] or [np.zeros(0, np.uint64)])
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64))], ["h"])
        _rest()

    counts = written(docs.select("text").mapInArrow(run, "h long").groupBy("h").count().where(F.col("count") >= opt.frequent), "frequent")
    level = F.floor(F.log2("count")).cast("int")
    by_level = {r.level: r.n for r in counts.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("n")).collect()}
    least, kept = 0, 0
    for at in sorted(by_level, reverse=True):
        if kept + by_level[at] > opt.max_frequent:
            break
        least, kept = at, kept + by_level[at]
    hot = counts.where(F.col("count") >= F.lit(float(2**least))).toArrow() if kept else None
    discard(counts)
    if hot is None:
        return NONE
    return Order(hot.column("h").to_numpy().view(np.uint64), hot.column("count").to_numpy())


def postings(docs: DataFrame, order: Order, opt: Options) -> DataFrame:
    """(h, node, meta): a row for each prefix shingle; meta packs set size and position."""
    held = docs.sparkSession.sparkContext.broadcast((order.frequent, order.counts))  # at most max_frequent

    def run(batches):
        arrange = Order(*held.value)
        for b in batches:
            sets = [s for s in shingle_sets(b.column(0).to_pylist(), opt) if len(s)]
            parts = [arrange(s)[: prefix_length(len(s), opt)] for s in sets]
            size = [len(p) for p in parts]
            h = np.concatenate(parts) if parts else np.zeros(0, np.uint64)
            node = np.repeat(np.asarray([node_of(s)[0] for s in sets], np.int64), size)
            meta = np.repeat(np.asarray([len(s) for s in sets], np.int64) << 32, size) + (np.concatenate([np.arange(k) for k in size]) if size else 0)
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(node), pa.array(meta)], ["h", "node", "meta"])
        _rest()

    return docs.select("text").mapInArrow(run, "h long, node long, meta long")


def _may_link(x: Column, y: Column, opt: Options) -> Column:
    """Length and positional filters on two packed sizes and positions."""
    nx, ny = F.shiftright(x, 32), F.shiftright(y, 32)
    px, py = x.bitwiseAND(F.lit(0xFFFFFFFF)), y.bitwiseAND(F.lit(0xFFFFFFFF))
    left = F.least(nx - px, ny - py)  # if this is the first shared shingle, no more can be shared
    return (opt.den * F.least(nx, ny) >= opt.num * F.greatest(nx, ny)) & ((opt.num + opt.den) * left >= opt.num * (nx + ny))


def _pairs(a: Column, b: Column) -> list[Column]:
    return [F.least(a, b).alias("a"), F.greatest(a, b).alias("b")]


def _all_pairs(short: DataFrame, may) -> DataFrame:
    """Pairs of rows (key, s array<struct>) of short lists that ``may`` link."""
    every = F.flatten(F.transform("s", lambda x, i: F.transform(F.slice(F.col("s"), i + 2, F.size("s")), lambda y: F.struct(x.alias("x"), y.alias("y")))))
    return short.select(F.explode(every).alias("p")).where(may(F.col("p.x"), F.col("p.y"))).select(*_pairs(F.col("p.x.node"), F.col("p.y.node"))).where("a <> b")


def with_hub(long: DataFrame) -> DataFrame:
    """Adds ``hub``: of a posting's sets, the one in most long postings."""
    score = long.groupBy("node").agg(F.count(F.lit(1)).alias("score"))
    return long.join(score, "node").withColumn("hub", F.max(F.struct("score", "node", "meta")).over(W.partitionBy("h"))).select("h", "node", "meta", "hub")


def first_pairs(shared: DataFrame, hubs: DataFrame, opt: Options) -> DataFrame:
    """All pairs of short postings, and every set of a long one with its hub."""
    short = shared.where(F.col("m") <= opt.short_posting).groupBy("h").agg(F.collect_list(F.struct("node", "meta")).alias("s"))
    near = _all_pairs(short, lambda x, y: _may_link(x["meta"], y["meta"], opt))
    star = hubs.where(_may_link(F.col("meta"), F.col("hub.meta"), opt)).select(*_pairs(F.col("node"), F.col("hub.node"))).where("a <> b")
    return near.unionByName(star).distinct()


def _suffix_admits(x: np.ndarray, y: np.ndarray, need: int, depth: int = 3) -> bool:
    """Suffix filter: halving both sorted sets at a pivot bounds how many elements differ."""

    def differ(x, y, most, depth):
        gap = abs(len(x) - len(y))
        if gap > most or depth == 0 or not len(x) or not len(y):
            return gap
        pivot = y[len(y) // 2]
        i, j = np.searchsorted(x, pivot), len(y) // 2
        low = differ(x[:i], y[:j], most, depth - 1)
        return low + differ(x[i:], y[j:], most - low, depth - 1) if low <= most else low

    most = len(x) + len(y) - 2 * need
    return differ(x, y, most, depth) <= most


def linked(x: np.ndarray, y: np.ndarray, opt: Options) -> bool:
    need = overlap_needed(len(x), len(y), opt)
    if min(len(x), len(y)) < need or not _suffix_admits(x, y, need):
        return False
    return len(np.intersect1d(x, y, assume_unique=True)) >= need


def with_texts(pairs: DataFrame, docs: DataFrame, sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(a, b, ta, tb), and the table of texts behind it. Only texts that a pair names are shuffled."""
    nodes = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
    named = written(sets.where("n > 0").groupBy("node").agg(F.min("row_key").alias("row_key")).join(nodes, "node", "left_semi"), "named")
    texts = only_keys(docs.select("row_key", "text"), named.select("row_key"))
    texts = written(texts.join(named, "row_key").select("node", "text"), "texts")
    discard(named)
    one, two = (texts.select(F.col("node").alias(c), F.col("text").alias(f"t{c}")) for c in "ab")
    return pairs.join(two, "b").join(one, "a").select("a", "b", "ta", "tb"), texts


def _sets_of_pairs(batches, opt: Options, most: int = 4 << 20):
    """Parts of each batch, of a few megabytes of text, with the two sets of each row; runs of one
    ``a`` share a set."""
    import pyarrow.compute as pc

    last = (None, None)
    for whole in batches:
        size = np.cumsum(pc.binary_length(whole.column("tb")).to_numpy()) // most
        edges = np.flatnonzero(np.concatenate([[True], size[1:] != size[:-1], [True]])) if len(size) else []
        for at, end in zip(edges, edges[1:]):
            b = whole.slice(int(at), int(end - at))
            first = []
            for i, node in enumerate(b.column("a").to_pylist()):
                if last[0] != node:
                    last = (node, shingle_sets([b.column("ta")[i].as_py()], opt)[0])
                first.append(last[1])
            yield b, first, shingle_sets(b.column("tb").to_pylist(), opt)


def verified(pairs: DataFrame, docs: DataFrame, sets: DataFrame, opt: Options) -> DataFrame:
    """The pairs of nodes whose whole sets link."""

    def run(batches):
        for b, xs, ys in _sets_of_pairs(batches, opt):
            yield b.select(["a", "b"]).filter(pa.array([linked(x, y, opt) for x, y in zip(xs, ys)], pa.bool_()))
        _rest()

    full, texts = with_texts(pairs, docs, sets)
    out = written(full.mapInArrow(run, "a long, b long"), "links")
    discard(texts)
    release(docs.sparkSession)
    return out


def beyond_hub(apart: DataFrame, docs: DataFrame, sets: DataFrame, order: Order, opt: Options) -> DataFrame:
    """(hub, node, c, n, i, rest) for ``apart(hub, node, c)``: set size, size of the intersection
    with the hub, and the prefix of what lies outside the hub."""
    held = docs.sparkSession.sparkContext.broadcast((order.frequent, order.counts))

    def run(batches):
        arrange = Order(*held.value)
        for b, hubs, ys in _sets_of_pairs(batches, opt):
            inside = [np.isin(y, x, assume_unique=True) for x, y in zip(hubs, ys)]
            rest = [arrange(y[~k])[: prefix_length(len(y), opt)].view(np.int64) for y, k in zip(ys, inside)]
            at = np.cumsum([0, *map(len, rest)])
            lists = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(np.concatenate([*rest, np.zeros(0, np.int64)]), pa.int64()))
            yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b"), pa.array([len(y) for y in ys], pa.int64()), pa.array([int(k.sum()) for k in inside], pa.int64()), lists], ["hub", "node", "n", "i", "rest"])
        _rest()

    full, texts = with_texts(apart.select(F.col("hub").alias("a"), F.col("node").alias("b")), docs, sets)
    rows = written(full.mapInArrow(run, "hub long, node long, n long, i long, rest array<long>"), "beyond")
    discard(texts)
    release(docs.sparkSession)
    return rows.join(apart, ["hub", "node"])


def still_apart(hubs: DataFrame, found: DataFrame) -> DataFrame:
    """(hub, node, c) for the sets of long postings that hold several classes. The hub is now the
    most linked set of the posting's most linked class, which lies nearer to what they share."""
    comp = components(found).select(F.col("id").alias("node"), F.col("component_id").alias("c"))
    ends = found.select(F.col("a").alias("node")).unionByName(found.select(F.col("b").alias("node"))).groupBy("node").agg(F.count(F.lit(1)).alias("degree"))
    top = comp.join(ends, "node").groupBy("c").agg(F.max(F.struct("degree", "node")).alias("top"))
    w = W.partitionBy("h")
    own = hubs.join(comp, "node", "left").withColumn("c", F.coalesce("c", "node"))
    own = own.withColumn("c0", F.min("c").over(w)).withColumn("c1", F.max("c").over(w)).where("c0 <> c1").join(top, "c", "left")
    near = F.max("top").over(w)["node"]
    return own.select("node", "c", F.coalesce(near, F.col("hub.node")).alias("hub")).select("hub", "node", "c").distinct()


def better_hubs(rows: DataFrame) -> DataFrame:
    """(hub, old, node, n, hub_n): each hub's sets under the one of them that holds most of what
    they share: shingles of the old hub, and shingles outside it that over half of them hold."""
    size = rows.groupBy("hub").agg(F.count(F.lit(1)).alias("size"))
    each = rows.select("hub", "node", F.explode("rest").alias("s"))
    often = each.groupBy("hub", "s").agg(F.count(F.lit(1)).alias("m")).join(size, "hub").where("2 * m > size").select("hub", "s")
    bonus = each.join(often, ["hub", "s"]).groupBy("hub", "node").agg(F.count(F.lit(1)).alias("bonus"))
    own = F.col("node") == F.col("hub")  # of the hub itself counts what another set confirms
    other = rows.where(~own).groupBy("hub").agg(F.max("i").alias("seen"))
    holds = F.when(own, F.coalesce("seen", "i")).otherwise(F.col("i") + F.coalesce("bonus", F.lit(0)))
    each = rows.join(bonus, ["hub", "node"], "left").join(other, "hub", "left")
    best = each.groupBy("hub").agg(F.max(F.struct(holds.alias("holds"), own.cast("int").alias("own"), (-F.col("n")).alias("size"), "node", "n")).alias("b"))
    return rows.select(F.col("hub").alias("old"), "node", "n").join(best.select(F.col("hub").alias("old"), F.col("b.node").alias("hub"), F.col("b.n").alias("hub_n")), "old")


def pairs_beyond(rows: DataFrame, opt: Options) -> DataFrame:
    """Pairs of sets of different classes that may still link, by the two cases of the hub's bound."""
    size = lambda x, y: opt.den * F.least(x["n"], y["n"]) >= opt.num * F.greatest(x["n"], y["n"])
    need = lambda x, y: opt.num * (x["n"] + y["n"])
    item = F.struct("node", "n", "i", "c")
    # what both share with the hub may suffice: each lies in the hub for the most part
    most = rows.where(F.col("i") * opt.den >= F.col("n") * opt.num).select("hub", item.alias("x"))
    x, y = most, most.withColumnRenamed("x", "y")
    both = x.join(y, "hub").where((F.col("x.node") < F.col("y.node")) & (F.col("x.c") != F.col("y.c")))
    both = both.where((opt.num + opt.den) * F.least("x.i", "y.i") >= need(F.col("x"), F.col("y"))).select(*_pairs(F.col("x.node"), F.col("y.node")))
    # else they share something outside it
    out = rows.select("hub", item.alias("v"), F.explode("rest").alias("s"))
    out = out.withColumn("m", F.count(F.lit(1)).over(W.partitionBy("hub", "s"))).where("m > 1")
    may = lambda x, y: (x["c"] != y["c"]) & size(x, y)
    short = out.where(F.col("m") <= opt.short_posting).groupBy("hub", "s").agg(F.collect_list("v").alias("s_"))
    near = _all_pairs(short.select(F.col("s_").alias("s")), may)
    x, y = (out.where(F.col("m") > opt.short_posting).select("hub", "s", F.col("v").alias(c)) for c in "xy")
    far = x.join(y, ["hub", "s"]).where((F.col("x.node") < F.col("y.node")) & may(F.col("x"), F.col("y"))).select(*_pairs(F.col("x.node"), F.col("y.node")))
    return both.unionByName(near).unionByName(far).distinct()


def links(docs: DataFrame, opt: Options = Options()) -> tuple[DataFrame, DataFrame]:
    """(rows with set size and node, links between nodes that connect every class) for keyed docs."""
    spark = docs.sparkSession
    sets = written(described(docs, opt), "sets")
    order = _frequent(docs, opt)
    release(spark)
    rows = postings(docs, order, opt).repartition("h").groupBy("h", "node").agg(F.first("meta").alias("meta"))
    shared = written(rows.withColumn("m", F.count(F.lit(1)).over(W.partitionBy("h"))).where("m > 1"), "shared")
    release(spark)
    hubs = written(with_hub(shared.where(F.col("m") > opt.short_posting)), "hubs")
    tried = written(first_pairs(shared, hubs, opt), "pairs")
    discard(shared)
    release(spark)
    found = verified(tried, docs, sets, opt)
    apart = still_apart(hubs, found)
    apart = written(apart, "apart")
    discard(hubs)
    if apart.head(1):
        rows = written(beyond_hub(apart, docs, sets, order, opt), "beyond")
        moved = written(better_hubs(rows), "moved")
        star = moved.where("hub <> old").where(opt.den * F.least("n", "hub_n") >= opt.num * F.greatest("n", "hub_n")).select(*_pairs(F.col("node"), F.col("hub"))).where("a <> b").distinct()
        star = written(star.join(tried, ["a", "b"], "left_anti"), "pairs")
        if star.head(1):
            found = written(found.unionByName(verified(star, docs, sets, opt)), "links")
            tried = written(tried.unionByName(star), "pairs")
        comp = components(found).select(F.col("id").alias("node"), F.col("component_id").alias("c"))
        w = W.partitionBy("hub")
        left = moved.select("hub", "old", "node").join(comp, "node", "left").withColumn("c", F.coalesce("c", "node"))
        left = written(left.withColumn("c0", F.min("c").over(w)).withColumn("c1", F.max("c").over(w)).where("c0 <> c1").select("hub", "old", "node", "c"), "apart")
        stay = left.where("hub = old").select("hub", "node", "c").join(rows.drop("c"), ["hub", "node"])
        went = left.where("hub <> old").select("hub", "node", "c").distinct()
        again = stay.unionByName(beyond_hub(went, docs, sets, order, opt).select(*stay.columns)) if went.head(1) else stay
        more = written(pairs_beyond(written(again, "beyond"), opt).join(tried, ["a", "b"], "left_anti"), "pairs")
        release(spark)
        if more.head(1):
            found = written(found.unionByName(verified(more, docs, sets, opt)), "links")
        for table in (rows, moved, left):
            discard(table)
    discard(tried)
    return sets, found


def classes(docs: DataFrame, opt: Options = Options()) -> DataFrame:
    """(row_key, doc_id, n_shingles, component_id, keeper) for keyed docs. ``keeper`` is the least
    row key of the class."""
    sets, found = links(docs, opt)
    comp = components(found)
    own = sets.join(comp.select(F.col("id").alias("node"), "component_id"), "node", "left")
    alone = F.when(F.col("component_id").isNull(), F.col("mark")).otherwise(F.lit(0))
    row = F.when(F.col("n") == 0, F.col("row_key")).otherwise(F.lit(0))
    own = own.select("row_key", "doc_id", "n", F.coalesce("component_id", "node").alias("c"), alone.alias("c2"), row.alias("c3"))
    least = own.groupBy("c", "c2", "c3").agg(F.min("doc_id").alias("component_id"), F.min("row_key").alias("keeper"))
    return own.join(least, ["c", "c2", "c3"]).select("row_key", "doc_id", F.col("n").alias("n_shingles"), "component_id", "keeper")


def keep_one(docs: DataFrame, opt: Options = Options()) -> DataFrame:
    """The documents, columns as they came, without all but the first of each class."""
    base, key = with_row_key(docs)
    slim = base.select(F.col(key).cast("long").alias("row_key"), F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    gone = written(classes(slim, opt).where("row_key <> keeper").select(F.col("row_key").alias(key)), "gone")
    release(docs.sparkSession)
    return base.join(gone, key, "left_anti").select(*docs.columns)


def op5_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Set size and class of every document."""
    docs = keyed(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    return classes(docs).select("doc_id", "n_shingles", "component_id")
