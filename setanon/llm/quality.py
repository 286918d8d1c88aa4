"""Quality by ordinal regression on graded ratings, over hashed text.

A cumulative-link model: one weight vector over hashed features of a text and ordered thresholds
between the grades. P(grade <= j) is the logistic of threshold j minus the score, so one fit gives
the expected grade and every tail probability.

Grades of the given labels: 0 toxic, 1 neither toxic nor good, 2 good. The fit reads a sample of
at most ``max_rows`` labelled documents (those whose ids have the least hashes); every other row is only scored. Weights are sparse over a fixed number of
buckets, so what is broadcast does not grow with the corpus.

Defined results: a null or blank text is scored by its (empty) features; labels with a null
quality and toxicity are not used; documents with no usable label anywhere are all kept with a
null score; repeated rows and null ids are scored row by row.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import small_batches, tidy
from .words import WordHasher, blocks

BITS = 22
#: Buckets above the hashed words, for the shape of a text.
SHAPES = 128
WIDTH = (1 << BITS) + SHAPES
GRADES = 3
#: First bytes of a word that are features too, so that inflected forms share weight.
PREFIXES = (4, 5)


@dataclass(frozen=True)
class Options:
    max_rows: int = 12_000
    rounds: int = 150
    rate: float = 0.15
    ridge: float = 1.0  # penalty of a word bucket's weight; a shape's is a four-hundredth of it
    min_docs: int = 8  # a word bucket in fewer sampled texts has no weight,
    min_z: float = 6.0  # nor one whose texts' grades differ less from the mean, in standard errors
    keep_tail: float = 0.5  # least P(grade >= 2) of a kept document


_CLASS = np.zeros(256, np.int8)
_CLASS[65:91] = 1  # capitals
_CLASS[48:58] = 2  # digits
for _lo, _hi in ((33, 48), (58, 65), (91, 97), (123, 127)):
    _CLASS[_lo:_hi] = 3  # punctuation
for _c in b"#*$%&|<>!":
    _CLASS[_c] = 4  # symbols


def features(texts: list[bytes], hasher: WordHasher) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature numbers of each text, and where each text's begin."""
    hashes, at = hasher.prefixed(texts, PREFIXES)
    n = np.diff(at)
    owner = np.repeat(np.arange(len(texts), dtype=np.int64), n) << BITS
    key = [np.unique(owner | (h >> np.uint64(64 - BITS)).astype(np.int64)) for h in hashes]
    distinct = np.bincount(key[0] >> BITS, minlength=len(texts))
    key = np.concatenate([key[0], *(k ^ (salt << 12) for salt, k in enumerate(key[1:], 1))])
    size = np.asarray([len(t) for t in texts], np.int64)
    kinds = _CLASS[np.frombuffer(b"".join(texts), np.uint8)] if size.sum() else np.zeros(0, np.int8)
    doc = np.repeat(np.arange(len(texts)), size)
    share = [np.bincount(doc[kinds == k], minlength=len(texts)) / np.maximum(size, 1) for k in (1, 2, 3, 4)]
    share.append(distinct / np.maximum(n, 1))
    shape = [np.minimum(15, (np.sqrt(s) * 16).astype(np.int64)) + 16 * i for i, s in enumerate(share)]
    shape.append(np.minimum(15, np.log2(n + 1).astype(np.int64)) + 16 * len(share))
    ids = np.concatenate([key & ((1 << BITS) - 1), *((1 << BITS) + s for s in shape)])
    owner = np.concatenate([key >> BITS, *(np.arange(len(texts)) for _ in shape)])
    order = np.argsort(owner, kind="stable")
    return ids[order].astype(np.int32), np.concatenate([[0], np.cumsum(np.bincount(owner, minlength=len(texts)))])


@dataclass(frozen=True)
class Model:
    """Sparse weights (ascending buckets) and thresholds."""

    bucket: np.ndarray
    weight: np.ndarray
    cuts: np.ndarray

    def scores(self, texts: list[bytes], hasher: WordHasher) -> np.ndarray:
        return np.concatenate([self._block(b, hasher) for b in blocks(texts)] or [np.zeros(0)])

    def _block(self, texts: list[bytes], hasher: WordHasher) -> np.ndarray:
        ids, at = features(texts, hasher)
        if not len(self.bucket):
            return np.zeros(len(texts))
        i = np.minimum(np.searchsorted(self.bucket, ids), len(self.bucket) - 1)
        total = np.concatenate([[0.0], np.cumsum(np.where(self.bucket[i] == ids, self.weight[i], 0.0))])
        return total[at[1:]] - total[at[:-1]]

    def tails(self, score: np.ndarray) -> np.ndarray:
        """P(grade >= j) for j = 1, 2, ...: one column each."""
        return 1 / (1 + np.exp(np.clip(self.cuts[None, :] - score[:, None], -40, 40)))


def fit(ids: np.ndarray, at: np.ndarray, grade: np.ndarray, opt: Options = Options(), grades: int = GRADES) -> Model:
    """Full-batch Adam on the negative log likelihood with a ridge penalty."""
    n = len(grade)
    # one number for each bucket there is; only ids of buckets that get a weight are gathered
    df, total = np.zeros(WIDTH, np.int32), np.zeros(WIDTH, np.int32)
    for i in range(0, n, 500):
        j = min(i + 500, n)
        part = ids[at[i] : at[j]]
        df += np.bincount(part, minlength=WIDTH).astype(np.int32)
        for g in range(1, grades):
            mine = np.repeat(grade[i:j] == g, np.diff(at[i : j + 1]))
            total += (g * np.bincount(part[mine], minlength=WIDTH)).astype(np.int32)
    z = (total / np.maximum(df, 1) - grade.mean()) * np.sqrt(df) / max(grade.std(), 1e-9)
    used = (df >= opt.min_docs) & (np.abs(z) >= opt.min_z)
    used[1 << BITS :] |= df[1 << BITS :] > 0
    del df, total, z
    bucket = np.flatnonzero(used)
    new = np.cumsum(used, dtype=np.int32) - 1
    row, col = [], []
    for i in range(0, n, 500):
        j = min(i + 500, n)
        part = ids[at[i] : at[j]]
        hit = used[part]
        row.append(np.repeat(np.arange(i, j), np.diff(at[i : j + 1]))[hit])
        col.append(new[part[hit]].astype(np.int64))
    row, col = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (row, col))
    del new, used
    k = len(bucket)
    ridge = np.where(bucket >= 1 << BITS, opt.ridge / 400, opt.ridge)
    share = np.cumsum(np.bincount(grade, minlength=grades))[:-1]
    base = np.log((share + 1) / (n - share + 1))
    # thresholds: the first, then the logarithms of the gaps keep them ordered
    p = np.concatenate([np.zeros(k), base[:1], np.log(np.maximum(np.diff(base), 0.1))])
    m, v = np.zeros_like(p), np.zeros_like(p)
    for step in range(1, opt.rounds + 1):
        w, gaps = p[:k], np.exp(p[k + 1 :])
        cuts = np.concatenate([p[k : k + 1], p[k] + np.cumsum(gaps)])
        f = np.bincount(row, w[col], n)
        edge = np.concatenate([[-np.inf], cuts, [np.inf]])
        with np.errstate(over="ignore"):
            hi, lo = 1 / (1 + np.exp(f - edge[grade + 1])), 1 / (1 + np.exp(f - edge[grade]))
        prob = np.maximum(hi - lo, 1e-9)
        dhi, dlo = hi * (1 - hi) / prob, lo * (1 - lo) / prob
        g = np.zeros_like(p)
        g[:k] = np.bincount(col, (dhi - dlo)[row], k) + ridge * w
        dcut = np.zeros(grades + 1)
        np.add.at(dcut, grade + 1, -dhi)
        np.add.at(dcut, grade, dlo)
        dcut = dcut[1:-1]
        g[k] = dcut.sum()
        g[k + 1 :] = np.cumsum(dcut[::-1])[::-1][1:] * gaps
        g /= n
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        rate = opt.rate * (1 if step < opt.rounds * 0.6 else 0.3)
        p = p - rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    gaps = np.exp(p[k + 1 :])
    return Model(bucket.astype(np.int32), p[:k].astype(np.float32), np.concatenate([p[k : k + 1], p[k] + np.cumsum(gaps)]))


def graded(labels: DataFrame) -> DataFrame:
    """(doc_id, grade): 0 toxic, 1 neither toxic nor good, 2 good. Equal ids keep the lowest grade."""
    q, t = F.col("quality"), F.coalesce(F.col("toxic"), F.lit(0))
    grade = F.when(t >= 1, 0).when(q.isNull(), None).when(q >= 1, 2).otherwise(1)
    rows = labels.select(F.col("doc_id").cast("long").alias("doc_id"), grade.cast("int").alias("grade"))
    return rows.where("doc_id IS NOT NULL AND grade IS NOT NULL").groupBy("doc_id").agg(F.min("grade").alias("grade"))


def sample(docs: DataFrame, ratings: DataFrame, opt: Options = Options()) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features and grades of at most ``max_rows`` labelled texts, on the driver."""
    small_batches(docs.sparkSession)
    # the labels of least hash are the sample; of rows with one id, the text of least hash is used
    place = F.xxhash64("doc_id")
    chosen = F.broadcast(ratings.orderBy(place, "doc_id").limit(opt.max_rows))  # bounded
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text")).join(chosen, "doc_id")
    texts = texts.groupBy("doc_id", "grade").agg(F.min_by("text", F.struct(F.xxhash64("text"), "text")).alias("text"))

    def run(batches):
        hasher = WordHasher(punctuation_is_space=True)
        for batch in batches:
            first = 0
            for block in blocks([t.encode() for t in batch.column(0).to_pylist()]):
                ids, at = features(block, hasher)
                lists = pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(ids, pa.int32()))
                part = batch.slice(first, len(block))
                first += len(block)
                yield pa.RecordBatch.from_arrays([part.column(1), part.column(2), lists], ["doc_id", "grade", "ids"])

    t = texts.orderBy("doc_id").select("text", "doc_id", "grade").mapInArrow(run, "doc_id long, grade int, ids array<int>").toArrow()
    lists = t.column("ids").chunks
    flat = np.concatenate([np.zeros(0, np.int32), *(c.flatten().to_numpy() for c in lists)])
    sizes = np.concatenate([np.zeros(0, np.int64), *(c.value_lengths().to_numpy() for c in lists)])
    return flat, np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64), t.column("grade").to_numpy().astype(np.int64)


def train(docs: DataFrame, labels: DataFrame, opt: Options = Options()) -> Model | None:
    ids, at, grade = sample(docs, graded(labels), opt)
    model = fit(ids, at, grade, opt) if len(grade) else None
    del ids, at, grade
    tidy()
    return model


def scored(docs: DataFrame, model: Model | None, opt: Options = Options(), into: str = "_rated") -> DataFrame:
    """Input columns plus ``into``: struct(expected_grade, p_not_toxic, p_good, kept)."""
    kind = "expected_grade double, p_not_toxic double, p_good double, kept boolean"
    if model is None:
        return docs.withColumn(into, F.struct(*(F.lit(None).cast("double").alias(c) for c in ("expected_grade", "p_not_toxic", "p_good")), F.lit(True).alias("kept")))
    small_batches(docs.sparkSession)
    held = docs.sparkSession.sparkContext.broadcast(model)  # at most min_docs-th of the sample's features

    def rate(series: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        hasher = WordHasher(punctuation_is_space=True)
        for texts in series:
            parts = (texts.iloc[i : i + 1000] for i in range(0, len(texts), 1000))
            score = [held.value.scores([(t or "").encode() for t in part], hasher) for part in parts]
            tail = held.value.tails(np.concatenate(score) if score else np.zeros(0))
            yield pd.DataFrame({"expected_grade": tail.sum(axis=1), "p_not_toxic": tail[:, 0], "p_good": tail[:, -1], "kept": tail[:, -1] >= opt.keep_tail})
        tidy()

    rate.__annotations__ = {"series": Iterator[pd.Series], "return": Iterator[pd.DataFrame]}
    return docs.withColumn(into, F.pandas_udf(rate, kind)(F.coalesce(F.col("text"), F.lit(""))))


def select_good(docs: DataFrame, labels: DataFrame, opt: Options = Options()) -> DataFrame:
    """The documents, columns as they came, that the model keeps."""
    into = "_rated"
    while into in docs.columns:
        into += "_"
    return scored(docs, train(docs, labels, opt), opt, into).where(F.col(into)["kept"]).select(*docs.columns)


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected grade, tail probabilities and the verdict for every document."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality", "toxic")
    return scored(docs, train(docs, labels)).select("doc_id", "_rated.*")
