"""Quality rules by weak supervision, in DataFrame functions only.

Each rule votes good, votes bad or abstains. Expectation-maximisation over the counts of vote
patterns (at most 3 to the number of rules, whatever the input) estimates how often each rule is
right for good and for bad texts; the posterior probability of "good" then replaces a filter
that asks every rule to pass.

Defined results: a null or blank text has no words, and no rule but length votes on it; repeated
rows and null ids are scored row by row; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, doc_text, written

WS = " \t\n\x0b\x0c\r"
#: Words in a window, for repeated wording.
WINDOW = 5


def words_of(text: Column) -> Column:
    bare = F.btrim(text, F.lit(WS))
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, r"[\x20\x09-\x0D]+"))


def repeated_words(words: Column, n: Column) -> Column:
    """Words inside a window of five that occurs at least twice in the text."""
    hashes = F.transform(F.sequence(F.lit(1), n - (WINDOW - 1)), lambda i: F.xxhash64(F.slice(words, i, WINDOW)))

    def covered(h: Column) -> Column:
        ranked = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def twins(s: Column) -> Column:
            same = lambda k, x: F.coalesce(F.get(s, k)["h"] == x["h"], F.lit(False))
            at = F.array_sort(F.transform(F.filter(s, lambda x, k: same(k - 1, x) | same(k + 1, x)), lambda x: x["i"]))
            return F.aggregate(
                at,
                F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("last")),
                lambda a, p: F.struct((a["n"] + F.least(F.lit(WINDOW), p - a["last"])).alias("n"), p.alias("last")),
                lambda a: a["n"],
            )

        return bind(ranked, twins)

    return F.when(n < WINDOW + 1, F.lit(0)).otherwise(
        bind(hashes, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(covered(h)))
    )


def bind(value: Column, then) -> Column:
    """Evaluate ``value`` once and use it several times in ``then``."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def measured(docs: DataFrame) -> DataFrame:
    """doc_id and the counts that rules read, in one pass without a shuffle."""
    t = F.col("text")
    w = doc_text(docs).select("doc_id", "text", words_of(t).alias("w"))
    w = w.withColumn("n_words", F.size("w"))
    lines = F.filter(F.split(t, "\n", -1), lambda x: F.btrim(x, F.lit(WS)) != "")
    return w.select(
        "doc_id",
        F.col("n_words").cast("long").alias("n_words"),
        F.char_length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.regexp_count(t, F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        bind(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
        repeated_words(F.col("w"), F.col("n_words")).cast("long").alias("n_repeat_words"),
        F.regexp_count(t, F.lit(r"\p{Lu}")).cast("long").alias("n_upper"),
        F.size(F.array_distinct("w")).cast("long").alias("n_distinct"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


@dataclass(frozen=True)
class Rule:
    """SQL conditions under which the rule votes; it abstains where neither holds."""

    name: str
    good: str
    bad: str


RULES = (
    Rule("length", "n_words >= 40", "n_words < 15"),
    Rule("symbols", "n_words >= 10 AND n_symbols * 100 <= word_chars", "n_symbols * 12 > word_chars"),
    Rule("lines", "n_words >= 40 AND n_dup_lines = 0", "n_dup_lines >= 3"),
    Rule("wording", "n_words >= 20 AND n_repeat_words * 50 <= n_words", "n_repeat_words * 8 > n_words"),
    Rule("word_length", "n_words >= 10 AND word_chars BETWEEN 3 * n_words AND 9 * n_words", "n_words > 0 AND (word_chars < 2 * n_words OR word_chars > 14 * n_words)"),
    Rule("capitals", "n_words >= 10 AND n_upper * 10 <= word_chars", "n_upper * 2 > word_chars"),
    Rule("variety", "n_words >= 20 AND n_distinct * 4 >= n_words", "n_words >= 20 AND n_distinct * 10 < n_words"),
)


def votes(features: DataFrame, rules=RULES) -> DataFrame:
    """Adds one column ``vote_<rule>`` of 1, -1 or 0."""
    return features.withColumns(
        {f"vote_{r.name}": F.when(F.expr(r.bad), F.lit(-1)).when(F.expr(r.good), F.lit(1)).otherwise(F.lit(0)) for r in rules}
    )


@dataclass(frozen=True)
class Accuracies:
    """log P(good) / P(bad), and for each rule the log ratio that a good or a bad vote adds."""

    prior: float
    good_vote: tuple[float, ...]
    bad_vote: tuple[float, ...]
    right_on_good: tuple[float, ...]
    right_on_bad: tuple[float, ...]


def estimate(patterns: list[tuple[tuple[int, ...], int]], rounds: int = 50, strength: float = 20.0) -> Accuracies:
    """EM over vote patterns and their counts. The prior belief (right nine times in ten, worth
    ``strength`` votes) fixes which class is called good; abstaining says nothing."""
    k = len(patterns[0][0]) if patterns else len(RULES)
    p, good, bad = 0.8, [0.9] * k, [0.7] * k
    for _ in range(rounds):
        n = g = 0.0
        num_g, den_g, num_b, den_b = [0.9 * strength] * k, [strength] * k, [0.7 * strength] * k, [strength] * k
        for pattern, count in patterns:
            logit = math.log(p / (1 - p))
            for j, v in enumerate(pattern):
                if v:
                    logit += math.log(good[j] / (1 - bad[j])) if v > 0 else math.log((1 - good[j]) / bad[j])
            q = 1 / (1 + math.exp(-max(-50.0, min(50.0, logit))))
            n, g = n + count, g + q * count
            for j, v in enumerate(pattern):
                if v:
                    den_g[j] += q * count
                    den_b[j] += (1 - q) * count
                    num_g[j] += q * count * (v > 0)
                    num_b[j] += (1 - q) * count * (v < 0)
        p = min(0.99, max(0.01, (g + 8) / (n + 10)))
        good = [min(0.995, max(0.05, a / b)) for a, b in zip(num_g, den_g)]
        bad = [min(0.995, max(0.05, a / b)) for a, b in zip(num_b, den_b)]
    return Accuracies(
        math.log(p / (1 - p)),
        tuple(math.log(a / (1 - b)) for a, b in zip(good, bad)),
        tuple(math.log((1 - a) / b) for a, b in zip(good, bad)),
        tuple(good),
        tuple(bad),
    )


def score(voted: DataFrame, acc: Accuracies, rules=RULES) -> DataFrame:
    """Adds ``quality``, the posterior probability that the text is good."""
    logit = F.lit(acc.prior)
    for r, up, down in zip(rules, acc.good_vote, acc.bad_vote):
        v = F.col(f"vote_{r.name}")
        logit = logit + F.when(v > 0, F.lit(up)).when(v < 0, F.lit(down)).otherwise(F.lit(0.0))
    return voted.withColumn("quality", 1 / (1 + F.exp(-logit)))


def weak_quality(features: DataFrame, rules=RULES) -> DataFrame:
    voted = votes(features, rules)
    names = [f"vote_{r.name}" for r in rules]
    counts = [(tuple(int(r[c]) for c in names), r["n"]) for r in voted.groupBy(*names).agg(F.count(F.lit(1)).alias("n")).collect()]
    return score(voted, estimate(sorted(counts)), rules)


def op10_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts, base verdict and the weak-supervision verdict of every document."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    features = written(measured(docs), "features")  # small, and read twice
    scored = weak_quality(features).withColumn("base_failed", base_failed())
    return scored.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed",
        (~F.col("base_failed") & (F.col("quality") >= 0.5)).alias("kept"), F.round("quality", 6).alias("quality"),
    )
