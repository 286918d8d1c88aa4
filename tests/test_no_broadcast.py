"""Records that are written down never reach the driver as a broadcast, however small their files are."""

from setanon.llm.common import written
from setanon.operators import lsh


def broadcast_of(df) -> list[str]:
    """What stands under each broadcast of the plan, as its first lines."""
    lines = df._jdf.queryExecution().executedPlan().toString().split("\n")
    return ["\n".join(lines[i : i + 6]) for i, x in enumerate(lines) if "BroadcastExchange" in x]


def test_buckets_are_broadcast_and_records_are_not(spark, monkeypatch):
    rows = [(f"r{i}", f"u{i % 50}", f"b{i % 7}", ["x"]) for i in range(400)] + [("alone", "u", "own", ["y"])]
    b = written(spark.createDataFrame(rows, "record_id string, user_id string, bucket_id string, items array<string>"), "buckets")
    told = []
    for most in (100, 3):  # the sizes are broadcast, and then too many for it
        monkeypatch.setattr(lsh, "BUCKETS", most)
        for unit in ("record", "user"):
            kept, small = lsh.split_small(b, 3, unit, keep_size=True, counted=True)
            gone = small.select("record_id", "bucket_id")
            assert all("HashAggregate" in x for x in broadcast_of(gone)) and len(broadcast_of(gone)) == (most == 100)
            told.append((kept.count(), [tuple(r) for r in gone.collect()], kept.agg({"_records": "sum"}).first()[0]))
    assert told == [told[0]] * 4 and told[0][:2] == (400, [("alone", "own")])
