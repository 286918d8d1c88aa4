"""Lexical retrieval packing: windows filled with a seed text and its nearest unused texts.

Texts are encoded once; document count, mean length and document frequencies are those of the
whole corpus, one number for each token of the vocabulary. Documents are dealt to the shards of the
index by content: the shards follow each other along the rarest tokens, so texts whose rarest shared
token is the same lie in one shard, whatever the size of the corpus. A token whose texts need
several shards deals them by their next rarest tokens. In a shard a BM25 inverted index over token
ids answers one query for each window: all tokens of the seed rank the unused documents of the
shard, which fill the window in that order; the last one is cut and its rest seeds the next window.
Documents of other shards are not asked: a seed misses neighbours that share only more frequent
tokens with it (the README gives the share found). Windows are full; what is left at a shard's end is
cut into windows of power-of-two length, which need no padding.

Defined results: null text is an empty text (the end id alone); rows that repeat an id are packed
one by one, in the order of their id and tokens; an empty table packs to nothing; a text longer
than a window runs over several.
"""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import doc_text, tidy, written
from .encoding import encoder, forget

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
#: Bits of a sequence id below the shard number.
SEQUENCE_BITS = 28


#: Keys of the document count and the token count beside the tokens' own, which are from 0.
N_DOCS, N_TOKENS = -1, -2
TOKENS = "doc_id long, ids binary"
#: Texts that are encoded at once.
SLICE = 2_000


@dataclass(frozen=True)
class CorpusStats:
    """What BM25 takes from the corpus: documents, their mean length, and for each token the number
    of documents that hold it."""

    n: int
    mean: float
    df: np.ndarray


class ShardIndex:
    """BM25 over the token ids of one shard's documents. Without ``stats`` they are the corpus."""

    def __init__(self, docs: list[np.ndarray], *, k1: float = 1.2, b: float = 0.75, query_terms: int | None = None, stats: CorpusStats | None = None):
        self.n, self.query_terms = len(docs), query_terms
        size = np.fromiter(map(len, docs), np.int64, self.n)
        flat = np.concatenate(docs).astype(np.int64) if self.n else np.zeros(0, np.int64)
        owner = np.repeat(np.arange(self.n), size)
        key = np.sort((flat << 24) | owner)  # by token, then document
        first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, np.int64)
        tf = np.diff(np.r_[first, len(key)])
        token, self.doc = key[first] >> 24, key[first] & 0xFFFFFF
        edge = np.flatnonzero(np.r_[True, token[1:] != token[:-1]]) if len(token) else np.zeros(0, np.int64)
        self.at = np.r_[edge, len(token)]
        df = np.diff(self.at)
        n, mean, held = (self.n, size.mean() if self.n else 1.0, df) if stats is None else (stats.n, stats.mean, stats.df[token[edge]])
        idf = np.log1p((n - held + 0.5) / (held + 0.5))
        norm = k1 * (1 - b + b * size / max(1.0, mean))
        self.weight = (np.repeat(idf, df) * tf * (k1 + 1) / (tf + norm[self.doc])).astype(np.float32).astype(np.float64)  # as bincount wants them
        # a row of all documents for each term that over a sixteenth of them hold: at most 16 cells for a posting
        self.row = np.full(len(df), -1, np.int32)
        wide = np.flatnonzero(df * 16 > self.n)
        self.row[wide] = np.arange(len(wide), dtype=np.int32)
        self.dense = np.zeros((len(wide), self.n), np.float32)
        hot = np.repeat(self.row, df)
        self.dense[hot[hot >= 0], self.doc[hot >= 0]] = self.weight[hot >= 0]
        # forward lists: the weightiest terms of each document, by term rank
        term = np.repeat(np.arange(len(df), dtype=np.int32), df)
        shared = np.repeat(df > 1, df)  # a term that no other document has retrieves nothing
        order = np.lexsort((-self.weight[shared], self.doc[shared]))
        self.term, doc = term[shared][order], self.doc[shared][order]
        self.own = np.searchsorted(doc, np.arange(self.n + 1))

    def scores(self, doc: int) -> np.ndarray:
        """BM25 of every document of the shard for the seed's terms, or its weightiest ``query_terms``."""
        terms = self.term[self.own[doc] : self.own[doc + 1]][: self.query_terms]
        if not len(terms):
            return np.zeros(self.n, np.float32)
        row = self.row[terms]
        total = self.dense[row[row >= 0]].sum(axis=0, dtype=np.float32)
        spans = [slice(a, b) for a, b in zip(self.at[terms[row < 0]].tolist(), self.at[terms[row < 0] + 1].tolist())]
        if spans:
            total = total + np.bincount(np.concatenate([self.doc[s] for s in spans]), np.concatenate([self.weight[s] for s in spans]), self.n)
        return total


def ranked(score: np.ndarray, first: int = 16):
    """Documents with a score, best first, ties by number; the first few before the rest is sorted."""
    hits = np.flatnonzero(score > 0)
    if len(hits) > 4 * first:
        edge = np.partition(score[hits], len(hits) - first)[len(hits) - first]
        top = hits[score[hits] >= edge]
        yield from top[np.lexsort((top, -score[top]))].tolist()
        hits = hits[score[hits] < edge]
    yield from hits[np.lexsort((hits, -score[hits]))].tolist()


def pack_shard(docs: list[np.ndarray], window: int = 2048, stats: CorpusStats | None = None) -> list[tuple[int, int, int, int, int]]:
    """Pieces (document, start, length, window number, offset) that cover all ids of the shard."""
    n, index, out = len(docs), ShardIndex(docs, stats=stats), []
    used = np.zeros(n, bool)
    left = sum(map(len, docs))
    order, nxt, seq = np.argsort([-len(d) for d in docs], kind="stable"), 0, 0
    rest: tuple[int, int] | None = None  # a cut document and where its rest starts
    plan = [window] * (left // window) + [1 << i for i in range(window.bit_length(), -1, -1) if left % window >> i & 1]
    for room in plan:
        offset, queue, seed = 0, None, None
        while offset < room:
            if rest is None:
                if queue is None and seed is not None:
                    s = index.scores(seed)
                    s[used] = 0
                    queue = ranked(s)
                doc = next(queue, None) if queue is not None else None
                if doc is None:  # no neighbour is left: the longest unused document
                    while used[order[nxt]]:
                        nxt += 1
                    doc = order[nxt]
                used[doc] = True
                rest = (int(doc), 0)
            doc, start = rest
            seed = doc if seed is None else seed
            take = min(room - offset, len(docs[doc]) - start)
            out.append((doc, start, take, seq, offset))
            offset += take
            rest = (doc, start + take) if start + take < len(docs[doc]) else None
        seq += 1
    return out


class _Counts:
    """Documents, tokens, and for each token the documents that hold it."""

    def __init__(self):
        self.df, self.n, self.total = np.zeros(0, np.int64), 0, 0

    def add(self, ids: np.ndarray) -> None:
        self.add_all(ids, [len(ids)])

    def add_all(self, flat: np.ndarray, sizes: list[int]) -> None:
        """Documents that follow each other. The last place of a token in its document stands for it,
        which needs no sorting."""
        most = int(flat.max()) + 1 if len(flat) else 0
        if most > len(self.df):
            self.df = np.append(self.df, np.zeros(most - len(self.df), np.int64))
        place, last, once, a = np.arange(len(flat)), np.zeros(len(self.df), np.int64), np.zeros(len(flat), bool), 0
        for n in sizes:
            ids, at = flat[a : a + n], place[a : a + n]
            last[ids] = at
            once[a : a + n] = last[ids] == at
            a += n
        self.df += np.bincount(flat[once], minlength=len(self.df))
        self.n, self.total = self.n + len(sizes), self.total + len(flat)

    def rows(self) -> tuple[np.ndarray, np.ndarray]:
        seen = np.flatnonzero(self.df)
        return np.r_[N_DOCS, N_TOKENS, seen], np.r_[self.n, self.total, self.df[seen]]


def id_type(tokenizer: str, end_id: int) -> str:
    """The narrowest type that holds the ids."""
    from tokenizers import Tokenizer

    most = max(Tokenizer.from_file(tokenizer).get_vocab(True).values(), default=0)
    return "<u2" if max(most, end_id) < 1 << 16 else "<u4"


def encoded(docs: DataFrame, tokenizer: str, end_id: int, kind: str = "<u4") -> DataFrame:
    """``docs(doc_id, text)`` with the token ids, closed by the end id, for the text. Each partition
    ends with a row of its counts, where ``token`` and ``count`` are not null."""

    def run(batches):
        closed, counts = encoder(tokenizer, False).closed, _Counts()
        none = pa.array([None], pa.list_(pa.int64()))
        names = ["doc_id", "ids", "token", "count"]
        for whole in batches:
            for first in range(0, whole.num_rows, SLICE):
                batch = whole.slice(first, SLICE)
                flat, sizes = closed(batch.column(1).to_pylist(), end_id)
                flat = flat.astype(kind)
                counts.add_all(flat, sizes.tolist())
                edge = np.r_[0, np.cumsum(sizes) * flat.itemsize].astype(np.int32)
                packed = pa.BinaryArray.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(edge), pa.py_buffer(flat)])
                gap = pa.nulls(len(sizes), pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([batch.column(0), packed, gap, gap], names)
        if counts.n:
            yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([None], pa.binary()), *(pa.array([x.tolist()], none.type) for x in counts.rows())], names)
        tidy()

    return docs.select("doc_id", "text").mapInArrow(run, f"{TOKENS}, token array<long>, count array<long>")


def corpus_stats(tokens: DataFrame, kind: str = "<u4") -> CorpusStats:
    """Counts of ``tokens(ids)``, or those that ``encoded`` left with them, added up in two steps; the
    driver gets one row for each token."""

    def run(batches):
        counts = _Counts()
        for batch in batches:
            for ids in batch.column(0):
                counts.add(np.frombuffer(ids.as_buffer(), kind))
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in counts.rows()], names=["token", "n"])

    if "count" in tokens.columns:
        each = tokens.where("count IS NOT NULL").select(F.explode(F.arrays_zip("token", "count")).alias("x")).select("x.token", F.col("x.count").alias("n"))
    else:
        each = tokens.select("ids").mapInArrow(run, "token long, n long")
    rows = each.groupBy("token").agg(F.sum("n").alias("n")).toArrow()
    token, count = (rows.column(c).to_numpy() for c in ("token", "n"))
    df = np.zeros(int(token.max(initial=0)) + 1, np.int64)
    df[token[token >= 0]] = count[token >= 0]
    n, total = (int(count[token == k].sum()) for k in (N_DOCS, N_TOKENS))
    return CorpusStats(n, total / max(1, n), df)


#: Rarest tokens of a text that say where it goes.
ROUTE = 4


def by_rareness(df: np.ndarray) -> np.ndarray:
    """For each token its place among those that several texts hold, rare ones first, ties by token;
    the others are at the end, all at one place."""
    several = int((df > 1).sum())
    place = np.full(len(df), several, np.int64)
    place[np.lexsort((np.arange(len(df)), np.where(df > 1, df, np.iinfo(np.int64).max)))[:several]] = np.arange(several)
    return place


def rarest(ids: np.ndarray, place: np.ndarray, several: int) -> list[int]:
    """Places of the ``ROUTE`` rarest tokens of a text that other texts hold too."""
    at, out = place[ids], []
    while len(out) < ROUTE:
        at = at[at > out[-1]] if out else at
        least = int(at.min(initial=several))
        if least >= several:
            break
        out.append(least)
    return out


def route_sizes(tokens: DataFrame, df: np.ndarray, kind: str) -> DataFrame:
    """(route, size): bytes of 32-bit ids of each route, without what only the dealing needs."""
    place = by_rareness(df)
    held = tokens.sparkSession.sparkContext.broadcast((place, int((df > 1).sum())))  # a number for each token of the vocabulary

    def run(batches):
        forget()  # all texts are encoded by now
        tidy()
        place, several = held.value
        for b in batches:
            ids = [np.frombuffer(x.as_buffer(), kind) for x in b.column(0)]
            least = np.asarray([place[x].min(initial=several) for x in ids], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.where(least < several, least, -1)), pa.array([4 * len(x) for x in ids], pa.int64())], ["route", "size"])

    return tokens.select("ids").mapInArrow(run, "route long, size long").groupBy("route").agg(F.sum("size").alias("size"))


def routed(tokens: DataFrame, df: np.ndarray, kind: str) -> DataFrame:
    """Adds to each text its route, the place of its rarest token (-1 if it has none), ``spread``, a
    hash of the next ones, and its size in bytes."""
    place = by_rareness(df)
    held = tokens.sparkSession.sparkContext.broadcast((place, int((df > 1).sum())))  # a number for each token of the vocabulary

    def run(batches):
        forget()  # all texts are encoded by now
        tidy()
        place, several = held.value
        for b in batches:
            route, spread, size = [], [], []
            for ids in b.column(1):
                ids = np.frombuffer(ids.as_buffer(), kind)
                way = rarest(ids, place, several)
                route.append(way[0] if way else -1)
                spread.append(zlib.crc32(np.asarray(way[1:], "<i8").tobytes() or ids.tobytes()))
                size.append(4 * len(ids))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(route, pa.int64()), pa.array(spread, pa.int64()), pa.array(size, pa.int64())], ["doc_id", "ids", "route", "spread", "size"])

    return tokens.select("doc_id", "ids").mapInArrow(run, f"{TOKENS}, route long, spread long, size long")


def shard_plan(sizes: list[tuple[int, int]], shard_bytes: int) -> dict[int, tuple[int, int]]:
    """(first shard, shards) of each route, for (route, bytes) in order: small routes share a shard,
    a large one has several of its own."""
    plan, shard, held = {}, 0, 0
    for route, size in sizes:
        if size > shard_bytes:
            shard += held > 0
            many = math.ceil(size / shard_bytes)
            plan[route] = (shard, many)
            shard, held = shard + many, 0
            continue
        if held and held + size > shard_bytes:
            shard, held = shard + 1, 0
        plan[route] = (shard, 1)
        held += size
    return plan


def dealt(tokens: DataFrame, stats: CorpusStats, shard_bytes: int, kind: str = "<u4") -> DataFrame:
    """(shard, doc_id, ids): the shards of about ``shard_bytes`` of 32-bit ids that follow the routes."""
    spark = tokens.sparkSession
    away = routed(tokens, stats.df, kind)
    sizes = route_sizes(tokens, stats.df, kind).orderBy("route").collect()  # as many at most
    plan = shard_plan([tuple(r) for r in sizes], shard_bytes)
    rows = [(route, first, many) for route, (first, many) in plan.items()]
    ways = F.broadcast(spark.createDataFrame(rows, "route long, first long, shards long"))
    return away.join(ways, "route").select((F.col("first") + F.pmod("spread", "shards")).alias("shard"), "doc_id", "ids")


def pack(docs: DataFrame, *, tokenizer: str, end_id: int = 1, window: int = 2048, shard_bytes: int = 3 << 20) -> DataFrame:
    """One row per piece."""
    kind = id_type(tokenizer, end_id)
    tokens = written(encoded(doc_text(docs), tokenizer, end_id, kind), "tokens")
    counts = corpus_stats(tokens)
    tokens = tokens.where("count IS NULL")
    stats = docs.sparkSession.sparkContext.broadcast(counts)

    def run(key, table):
        forget()
        shard = key[0].as_py()
        table = table.sort_by([("doc_id", "ascending"), ("ids", "ascending")])
        ids = [np.frombuffer(d, kind).astype("<u4") for d in table.column("ids").to_pylist()]
        cols = list(zip(*pack_shard(ids, window, stats.value))) or [()] * 5
        name = table.column("doc_id").to_pylist()
        crc = [zlib.crc32(ids[d][s : s + k].tobytes()) for d, s, k in zip(*cols[:3])]
        tidy()
        return pa.table(
            {
                "doc_id": pa.array([name[d] for d in cols[0]], pa.int64()),
                "start": pa.array(cols[1], pa.int64()),
                "length": pa.array(cols[2], pa.int64()),
                "ids_crc32": pa.array(crc, pa.int64()),
                "doc_tokens": pa.array([len(ids[d]) for d in cols[0]], pa.int64()),
                "sequence_id": pa.array([shard << SEQUENCE_BITS | q for q in cols[3]], pa.int64()),
                "offset": pa.array(cols[4], pa.int64()),
            }
        )

    return dealt(tokens, counts, shard_bytes, kind).groupBy("shard").applyInArrow(run, PIECES)


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's token ids packed into windows of at most 2,048."""
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return pack(docs, tokenizer=public_tokenizers.path("word_bpe_49k.json"))
