"""The SQL surface: functions that Catalyst sees through, an aggregate, and a table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def majority_set(sets: pd.Series) -> list:
    """Group target by majority, as a grouped aggregate; the native two-step form is the default."""
    from collections import Counter

    rows = [set(s) for s in sets if s is not None]
    c = Counter(x for s in rows for x in s)
    return sorted(x for x, n in c.items() if 2 * n > len(rows))


majority_set.__annotations__ = {"sets": pd.Series, "return": list}


class KGroups:
    """``k_groups(TABLE(t) PARTITION BY (bucket), k)`` for a table (bucket, record_id, items): yields
    the group of each record, by the suppression kernel."""

    def __init__(self):
        self.rows, self.k = [], 2

    def eval(self, row, k: int):
        self.rows.append((row["record_id"], list(row["items"]), row["bucket"]))
        self.k = k

    def terminate(self):
        if not self.rows:  # tasks without a partition end here too
            return
        from ..operators.kernel import SolveOptions, solve

        ids, sets = [r[0] for r in self.rows], [r[1] for r in self.rows]
        for record, group, goal in solve(ids, ids, sets, SolveOptions(self.k)):
            yield self.rows[0][2], record, group, goal


def register(spark: SparkSession) -> None:
    """Register set_hamming, set_jaccard, minhash_key, keyword_token, majority_set and k_groups."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_hamming(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS INT RETURN size(a) + size(b) - 2 * size(array_intersect(a, b))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_jaccard(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN CASE WHEN size(array_union(a, b)) = 0 THEN 1.0D ELSE size(array_intersect(a, b)) / size(array_union(a, b)) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION minhash_key(items ARRAY<STRING>, p INT) RETURNS STRING RETURN array_join(transform(sequence(0, p - 1), s -> cast(array_min(transform(items, x -> xxhash64(s, x))) AS STRING)), '-')")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION keyword_token(word STRING) RETURNS STRING RETURN array_join(transform(sequence(1000, 1001), s -> cast(array_min(transform(transform(filter(split(word, ''), c -> c <> ''),"
        " (c, i) -> concat(c, cast(size(filter(slice(filter(split(word, ''), d -> d <> ''), 1, i + 1), d -> d = c)) AS STRING))), x -> xxhash64(s, x))) AS STRING)), '-')"
    )
    spark.udf.register("majority_set", F.pandas_udf(majority_set, "array<string>"))
    spark.udtf.register("k_groups", F.udtf(KGroups, returnType="bucket string, record_id string, group_id string, target array<string>"))
