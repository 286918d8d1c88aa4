"""Secrets: three base kinds by pattern, and multipart credentials by linking their parts.

Weak candidates (a labelled identifier, a mixed-class run of characters, an address) mean little
alone. Within a scope, the part of a text between blank lines, each candidate is joined with the
complementary parts whose intervals lie within ``reach`` before or behind it; only candidates that
find a complement are reported. Matches run to their natural end, whatever their length. An endpoint
complements a linked part or a base secret; beside a weak
secret alone it stays unreported. The join looks intervals up by their sorted starts and ends, never all pairs.

Defined results: null text is an empty text; offsets are code points, end exclusive; base spans
are never changed by linking; repeated rows and null ids are scanned row by row.
"""

from __future__ import annotations

import bisect
import hashlib
import re
from dataclasses import dataclass

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import doc_text, small_batches

ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
_HINT = re.compile(r"(?i:passw|secret|token|api_?key)", re.A)

WEAK_ID = re.compile(r"""(?i:access_?key(?:_?id)?|key_?id|client_?id|account(?:_?id)?|user(?:name)?|login)["']?\x20*[:=]\x20*["']?([A-Za-z0-9._@+-]{4,})""", re.A)
WEAK_SECRET = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{16,}(?![A-Za-z0-9+/_=-])")
ENDPOINT = re.compile(r"(?:https?|wss?|jdbc:\w+|postgres|mysql|mongodb|redis|amqp|s3)://[^\s\"'<>]{4,}|\b(?:\d{1,3}\.){3}\d{1,3}:\d{2,5}\b", re.A)
_SCOPE = re.compile(r"\n[ \t\r]*\n")

#: In the order of the span lists.
KINDS = ("assign", "access", "hex", "linked_id", "linked_secret", "linked_endpoint")


@dataclass(frozen=True)
class Span:
    kind: str
    start: int
    end: int


def base_spans(text: str) -> list[Span]:
    out = []
    if _HINT.search(text):
        out += [Span("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[1]) >= 6]
    if "AKIA" in text:
        out += [Span("access", *m.span()) for m in ACCESS.finditer(text) if len(m[0]) >= 20]
    out += [Span("hex", *m.span()) for m in HEX.finditer(text)]
    return out


def _mixed(run: str) -> bool:
    """Digits and letters of both cases, as in generated keys."""
    return bool(re.search(r"\d", run) and re.search(r"[a-z]", run) and re.search(r"[A-Z]", run))


class _Parts:
    """Intervals of one part kind, which may overlap, by start and by end."""

    def __init__(self, spans: list[tuple[int, int]]):
        self.by_start = sorted(spans)
        self.by_end = sorted(spans, key=lambda x: (x[1], x[0]))
        self.starts, self.ends = [s for s, _ in self.by_start], [e for _, e in self.by_end]

    def near(self, start: int, end: int, reach: int, scope: tuple[int, int]) -> bool:
        """Is there a part of the scope that ends at most ``reach`` before the interval, or starts at
        most so far behind it? All parts within reach are looked at."""
        before = self.by_end[bisect.bisect_left(self.ends, start - reach) : bisect.bisect_right(self.ends, start)]
        behind = self.by_start[bisect.bisect_left(self.starts, end) : bisect.bisect_right(self.starts, end + reach)]
        return any(scope[0] <= s for s, _ in before) or any(e <= scope[1] for _, e in behind)


def linked_spans(text: str, base: list[Span], reach: int = 200) -> list[Span]:
    """Weak candidates whose complementary part lies within reach in the same scope."""
    strong_id = [(s.start, s.end) for s in base if s.kind == "access"]
    strong_secret = [(s.start, s.end) for s in base if s.kind != "access"]
    weak_id = [m.span() for m in WEAK_ID.finditer(text)]
    if not (strong_id or weak_id or strong_secret):
        return []  # a weak secret or an endpoint alone links to nothing
    taken = _Overlaps([(s.start, s.end) for s in base])
    weak_id = [s for s in weak_id if not taken.hit(*s)]
    taken_ids = _Overlaps(weak_id)
    weak_secret = [m.span() for m in WEAK_SECRET.finditer(text) if _mixed(m[0]) and not taken.hit(*m.span()) and not taken_ids.hit(*m.span())]
    points = [m.span() for m in ENDPOINT.finditer(text) if not taken.hit(*m.span())]
    cuts = [0, *(m.end() for m in _SCOPE.finditer(text)), len(text)]

    def scope(at: int) -> tuple[int, int]:
        i = bisect.bisect_right(cuts, at)
        return (cuts[i - 1], cuts[i]) if i < len(cuts) else (cuts[-2], cuts[-1])

    ids, secrets = _Parts(strong_id + weak_id), _Parts(strong_secret + weak_secret)
    out = [Span("linked_id", s, e) for s, e in weak_id if secrets.near(s, e, reach, scope(s))]
    out += [Span("linked_secret", s, e) for s, e in weak_secret if ids.near(s, e, reach, scope(s))]
    linked = _Parts([(x.start, x.end) for x in out] + strong_secret + [(s, e) for s, e in strong_id if secrets.near(s, e, reach, scope(s))])
    out += [Span("linked_endpoint", s, e) for s, e in points if linked.near(s, e, reach, scope(s))]
    return out


class _Overlaps:
    """Does an interval meet any of a list of disjoint ones?"""

    def __init__(self, spans: list[tuple[int, int]]):
        self.top, end = [], -1
        for s, e in sorted(spans):
            end = max(end, e)
            self.top.append((s, end))

    def hit(self, start: int, end: int) -> bool:
        i = bisect.bisect_left(self.top, (end, -1)) - 1
        return i >= 0 and self.top[i][1] > start


def scan(text: str | None, reach: int = 200) -> list[Span]:
    text = text or ""
    base = base_spans(text)
    return sorted(base + linked_spans(text, base, reach), key=lambda s: (s.start, KINDS.index(s.kind), s.end))


def listed(spans: list[Span]) -> str:
    return ",".join(f"{s.kind}:{s.start}:{s.end}" for s in spans)


def redacted(text: str | None, mark: str = "[SECRET]") -> str | None:
    """The text with every span, overlapping ones as one, replaced by the mark."""
    spans = scan(text)
    if not spans:
        return text
    out, at = [], 0
    for s in spans:
        if s.start >= at:
            out += [text[at : s.start], mark]
        at = max(at, s.end)
    return "".join(out) + text[at:]


FOUND = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string"


def find(docs: DataFrame, reach: int = 200) -> DataFrame:
    def run(batches):
        schema = pa.schema([("doc_id", pa.int64()), *((f"n_{k}", pa.int64()) for k in KINDS[:3]), ("base_sha256", pa.string()), ("spans", pa.string())])
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                spans = scan(text, reach)
                base = [s for s in spans if s.kind in KINDS[:3]]
                counts = [sum(s.kind == k for s in base) for k in KINDS[:3]]
                rows.append((doc_id, *counts, hashlib.sha256(listed(base).encode()).hexdigest(), listed(spans)))
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * 6, schema)], schema=schema)

    return doc_text(docs).mapInArrow(run, FOUND)


def redact(docs: DataFrame) -> DataFrame:
    """The documents with secrets masked; n_chars follows the text where the column is there."""
    small_batches(docs.sparkSession)

    @F.pandas_udf("string")
    def masked(texts: pd.Series) -> pd.Series:
        return pd.Series([redacted(t) for t in texts], dtype=object)

    out = docs.withColumn("text", masked("text"))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base and linked secrets of every document."""
    return find(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
