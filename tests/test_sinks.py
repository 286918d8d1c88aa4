import pytest

from setanon.sources import sinks, tables


@pytest.mark.parametrize("fmt", ["parquet", "orc", "json", "csv"])
def test_round_trip(spark, tmp_path, fmt):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "k long, v string")
    sinks.release(df, str(tmp_path / f"t.{fmt}"), fmt=fmt)
    back = tables.load(spark, str(tmp_path), "t", fmt=fmt, schema="k long, v string")
    assert sorted(map(tuple, back.collect())) == [(1, "a"), (2, "b")]
    if fmt in ("csv", "json"):
        with pytest.raises(ValueError):
            tables.load(spark, str(tmp_path), "t", fmt=fmt)


def test_partitions_and_buckets(spark, tmp_path):
    df = spark.createDataFrame([(i, f"p{i % 2}") for i in range(10)], "k long, p string")
    sinks.release(df, str(tmp_path / "p"), partition_by=("p",))
    one = spark.read.parquet(str(tmp_path / "p")).where("p = 'p1'")
    assert one.count() == 5 and "PartitionFilters: [isnotnull(p" in one._jdf.queryExecution().executedPlan().toString()
    with pytest.raises(Exception):
        sinks.release(df, str(tmp_path / "p"))
