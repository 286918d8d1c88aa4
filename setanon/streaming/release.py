"""Structured Streaming: records from events, buffered release by bucket, and micro-batches.

A bucket holds its records until k of them (or of distinct users) are there, solves them together
and publishes all. Its published sets are kept, as sets only; a later record may join by becoming
exactly one of them, so no published set ever has fewer than k records. What has not found k by the
watermark is deleted, as small clusters are.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import lsh_key
from ..operators.kernel import SolveOptions, solve
from ..plans.pipeline import AnonOptions, anonymize


def event_stream(spark: SparkSession, folder: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Replays a folder of Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def window_records(events: DataFrame, size: str, *, slide: str | None = None, gap: str | None = None, watermark: str = "1 day") -> DataFrame:
    """A record for each user and window: the set of event types. Tumbling by default, sliding with
    ``slide``, by sessions with ``gap``. Events later than the watermark never enter."""
    w = F.session_window("ts", gap) if gap else F.window("ts", size, slide) if slide else F.window("ts", size)
    g = events.withWatermark("ts", watermark).groupBy("user_id", w.alias("w")).agg(F.collect_set("event_type").alias("items"))
    return g.select(F.concat_ws("@", F.col("user_id").cast("string"), F.col("w.start").cast("string")).alias("record_id"), F.col("user_id").cast("string").alias("user_id"), F.array_sort("items").alias("items"), F.col("w.end").alias("ts"))


def first_copies(events: DataFrame, key: str, watermark: str) -> DataFrame:
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([key])


def with_items(events: DataFrame, dictionary: DataFrame, on: str) -> DataFrame:
    """A stream with a static item table."""
    return events.join(dictionary, on)


RELEASED = "record_id string, user_id string, bucket_id string, items array<string>, target array<string>, status string"
STATE = "record_ids array<string>, user_ids array<string>, sets array<string>, published array<string>"
_SEP = "\x1f"


def _join(x) -> str:
    return _SEP.join(sorted(x))


def _split(x: str) -> list[str]:
    return x.split(_SEP) if x else []


class Holder:
    """One bucket's waiting records and published sets; plain data in and out."""

    def __init__(self, k: int, unit: str = "record", options: SolveOptions | None = None):
        self.k, self.unit, self.options = k, unit, options or SolveOptions(k, unit=unit)

    def step(self, state: tuple | None, rows: list[tuple[str, str, list[str]]]) -> tuple[tuple, list[tuple]]:
        """New state and released rows (record, user, items, target)."""
        ids, users, sets, published = (list(x) for x in state) if state else ([], [], [], [])
        out = []
        for r, u, items in rows:
            if published:
                mine = set(items)
                goal = min(published, key=lambda p: (len(mine ^ set(_split(p))), p))
                # joining is right only when it costs no more than the set itself would lose
                if len(mine ^ set(_split(goal))) <= len(mine):
                    out.append((r, u, list(items), _split(goal)))
                    continue
            ids.append(r)
            users.append(u)
            sets.append(_join(items))
        held = len(set(users)) if self.unit == "user" else len(ids)
        if held >= self.k:
            by = dict(zip(ids, zip(users, sets)))
            for r, _, goal in solve(ids, users, [_split(s) for s in sets], self.options):
                out.append((r, by[r][0], _split(by[r][1]), goal))
                published.append(_join(goal))
            ids, users, sets, published = [], [], [], sorted(set(published))
        return (ids, users, sets, published), out


def buffered_release(records: DataFrame, k: int, *, p: int = 1, unit: str = "record", expire: str | None = None) -> DataFrame:
    """Rows of RELEASED from a stream of records with a watermark on ``ts``: released or expired."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    keyed = records.withColumn("bucket_id", lsh_key(F.col("items"), p))
    wait = pd.Timedelta(expire).value // 10**6 if expire else None

    def run(key, frames, state):
        holder = Holder(k, unit)
        if state.hasTimedOut:
            ids, users, sets, published = state.get
            rows = [(r, u, key[0], _split(s), [], "expired") for r, u, s in zip(ids, users, sets)]
            state.update(([], [], [], list(published)))
            yield pd.DataFrame(rows, columns=["record_id", "user_id", "bucket_id", "items", "target", "status"])
            return
        new, latest = [], 0
        for f in frames:
            new += list(zip(f["record_id"], f["user_id"], [list(x) for x in f["items"]]))
            latest = max(latest, int(f["ts"].max().timestamp() * 1000)) if len(f) else latest
        kept, out = holder.step(state.get if state.exists else None, sorted(new))
        state.update(kept)
        if wait is not None and kept[0]:
            state.setTimeoutTimestamp(max(latest, state.getCurrentWatermarkMs()) + wait + 1)
        rows = [(r, u, key[0], i, t, "released") for r, u, i, t in out]
        yield pd.DataFrame(rows, columns=["record_id", "user_id", "bucket_id", "items", "target", "status"])

    timeout = GroupStateTimeout.EventTimeTimeout if wait is not None else GroupStateTimeout.NoTimeout
    return keyed.groupBy("bucket_id").applyInPandasWithState(run, RELEASED, STATE, "append", timeout)


def batch_release(k: int, sink: Callable[[DataFrame, int], None], o: AnonOptions = AnonOptions(p=1)) -> Callable[[DataFrame, int], None]:
    """For ``foreachBatch``: each micro-batch is anonymized by itself and audited before the sink."""
    from ..operators.measures import audit

    def run(batch: DataFrame, number: int) -> None:
        r = anonymize(batch.select("record_id", "user_id", "items"), k, o)
        if audit(r.records, k, o.unit).first().violations:
            raise RuntimeError(f"batch {number} is not {k}-anonymous")
        sink(r.records, number)
        r.unpersist()

    return run
