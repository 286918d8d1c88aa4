"""Language by mixture inference.

Each language has a distribution over hashed byte n-grams, counted over all training texts. A text
is a mixture: expectation-maximisation finds the proportions that make its n-grams likeliest, and
languages are dropped one by one while the likelihood, less a penalty for each language, rises.

Defined results: a text that is null or has no letters is ``und`` with score 0 and no languages;
rows with a null id or a null language teach nothing, and a null id is not held out; without any
training text everything is ``und``; repeated rows are predicted row by row.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_mod3

#: ASCII bytes that are not letters count as spaces.
_FOLD = bytes(b if b > 127 or chr(b).isalpha() else 32 for b in range(256))


@dataclass(frozen=True)
class Options:
    n: int = 4  # bytes of an n-gram
    bits: int = 16  # buckets of n-grams
    smoothing: float = 0.5
    penalty: float = 2.0  # times log(n-grams), for each language of a text
    rounds: int = 40


def ngrams(text: str, opt: Options = Options()) -> np.ndarray:
    """Bucket of every n-gram of the lower-cased text, outer spaces included."""
    data = b" " + text.lower().encode("utf-8", "replace").translate(_FOLD) + b" "
    b = np.frombuffer(data, np.uint8).astype(np.uint32)
    m = len(b) - opt.n + 1
    if m <= 0:
        return np.zeros(0, np.uint16)
    h = np.zeros(m, np.uint32)
    for i in range(opt.n):
        h = h * np.uint32(0x01000193) + b[i : i + m]
    h *= np.uint32(0x9E3779B1)
    return (h >> np.uint32(32 - opt.bits)).astype(np.uint16 if opt.bits <= 16 else np.uint32)


@dataclass(frozen=True)
class Model:
    langs: tuple[str, ...]
    probs: np.ndarray  # bucket x language

    def mixture(self, text: str | None, opt: Options = Options()) -> list[tuple[str, float]]:
        """Languages of the text with their shares, the largest first."""
        if not text or not self.langs or not any(map(str.isalpha, text)):
            return []
        grams = ngrams(text, opt)
        if len(grams) > 1 << opt.bits:
            c = np.bincount(grams, minlength=1 << opt.bits)
            bucket = np.flatnonzero(c)
            c = c[bucket]
        else:
            bucket, c = np.unique(grams, return_counts=True)
        shares = infer(self.probs[bucket], c.astype(np.float64), opt)
        return sorted(((self.langs[i], float(s)) for i, s in shares.items()), key=lambda x: (-x[1], x[0]))


def em(p: np.ndarray, c: np.ndarray, rounds: int) -> tuple[np.ndarray, float]:
    """Shares of the columns of ``p`` that make the counts likeliest, and the log likelihood."""
    share = np.full(p.shape[1], 1 / p.shape[1])
    if len(share) == 1:
        return share, float(c @ np.log(p[:, 0]))
    weight, total = c / c.sum(), c.sum()
    for _ in range(rounds):
        new = share * (p.T @ (weight / (p @ share)))
        done = np.abs(new - share).max() < 1e-4
        share = new
        if done:
            break
    return share, float(total * (weight @ np.log(p @ share)))


def infer(p: np.ndarray, c: np.ndarray, opt: Options) -> dict[int, float]:
    """Backward selection of the language set by penalised likelihood."""
    cost = opt.penalty * np.log(c.sum() + 1)
    keep = np.arange(p.shape[1])
    share, fit = em(p, c, opt.rounds)
    while len(keep) > 1:
        # what hardly takes part goes at once, else the least share
        drop = share < 0.01 if (share < 0.01).any() and (share >= 0.01).any() else np.arange(len(share)) == share.argmin()
        less = keep[~drop]
        share2, fit2 = em(p[:, less], c, opt.rounds)
        if fit2 + cost * drop.sum() < fit:
            break
        keep, share, fit = less, share2, fit2
    share = share / share.sum()
    return {int(k): s for k, s in zip(keep, share)}


def learn(docs: DataFrame, opt: Options = Options()) -> Model:
    """Counts over the rows of ``docs(text, lang)``; at most buckets x languages rows reach the driver."""

    def run(batches):
        total: dict[str, np.ndarray] = {}
        for b in batches:
            for text, lang in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                if lang not in total:
                    total[lang] = np.zeros(1 << opt.bits, np.int64)
                g = ngrams(text, opt)
                if len(g) > 20_000:
                    total[lang] += np.bincount(g, minlength=1 << opt.bits)
                else:
                    np.add.at(total[lang], g, 1)
        for lang, c in total.items():
            at = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at.astype(np.int32)), pa.array(c[at])], ["lang", "bucket", "n"])

    rows = docs.where("text IS NOT NULL AND lang IS NOT NULL").select("text", F.col("lang").cast("string").alias("lang"))
    t = rows.mapInArrow(run, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    names = t.column("lang").to_pylist()
    langs = tuple(sorted(set(names)))
    counts = np.full((1 << opt.bits, len(langs)), opt.smoothing)
    where = {x: i for i, x in enumerate(langs)}
    if langs:
        np.add.at(counts, (t.column("bucket").to_numpy(), np.asarray([where[x] for x in names])), t.column("n").to_numpy())
    return Model(langs, counts / counts.sum(axis=0, keepdims=True) if langs else counts)


PREDICTED = "doc_id long, held_out boolean, lang_pred string, score double, shares string"


def predict(docs: DataFrame, model: Model, opt: Options = Options()) -> DataFrame:
    """lang_pred is the language of the largest share, score that share; shares lists them all."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # buckets x languages

    def run(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("lang_pred", pa.string()), ("score", pa.float64()), ("shares", pa.string())])
        for b in batches:
            mixes = [held.value.mixture(t, opt) for t in b.column(2).to_pylist()]
            top = [m[0] if m else ("und", 0.0) for m in mixes]
            listed = [",".join(f"{k}:{s:.4f}" for k, s in m) for m in mixes]
            yield pa.RecordBatch.from_arrays(
                [b.column(0).cast(pa.int64()), b.column(1), pa.array([k for k, _ in top], pa.string()), pa.array([min(1.0, s) for _, s in top], pa.float64()), pa.array(listed, pa.string())],
                schema=schema,
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(crc_mod3(F.col("doc_id")) == 1, F.lit(False)).alias("held_out"), "text")
    return rows.mapInArrow(run, PREDICTED)


def op1_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of every document, learned from two thirds of the ids."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    model = learn(docs.where(crc_mod3(F.col("doc_id")) != 1).select("text", "lang"))
    return predict(docs.select("doc_id", "text"), model)
