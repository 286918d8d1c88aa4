"""What a released data set is still good for."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def frequent_itemsets(recs: DataFrame, min_support: float) -> DataFrame:
    """(items, freq) by FP-growth, items joined in order."""
    from pyspark.ml.fpm import FPGrowth

    sets = recs.where(F.size("items") > 0).select("items")
    return FPGrowth(itemsCol="items", minSupport=min_support).fit(sets).freqItemsets.select(F.concat_ws("|", F.array_sort("items")).alias("items"), "freq")


def itemset_utility(before: DataFrame, after: DataFrame, min_support: float) -> DataFrame:
    """One row: frequent itemsets before, after and in both; precision and recall."""
    a = frequent_itemsets(before, min_support).select("items", F.lit(1).alias("was"))
    b = frequent_itemsets(after, min_support).select("items", F.lit(1).alias("now"))
    j = a.join(b, "items", "full").agg(F.coalesce(F.sum("was"), F.lit(0)).alias("n_before"), F.coalesce(F.sum("now"), F.lit(0)).alias("n_after"), F.count_if(F.col("was").isNotNull() & F.col("now").isNotNull()).alias("n_both"))
    return j.withColumn("precision", F.round(F.col("n_both") / F.greatest("n_after", F.lit(1)), 6)).withColumn("recall", F.round(F.col("n_both") / F.greatest("n_before", F.lit(1)), 6))


def suggestions(recs: DataFrame, n: int = 5) -> DataFrame:
    """(item, suggestion): the n items that most often come with an item, ties in order."""
    e = recs.select("record_id", F.explode("items").alias("item"))
    p = e.join(e.withColumnRenamed("item", "suggestion"), "record_id").where("item <> suggestion").groupBy("item", "suggestion").count()
    return p.withColumn("r", F.row_number().over(W.partitionBy("item").orderBy(F.desc("count"), "suggestion"))).where(F.col("r") <= n).select("item", "suggestion")


def suggestion_utility(before: DataFrame, after: DataFrame, n: int = 5) -> DataFrame:
    """One row: suggestions before, and the share that survives."""
    a, b = suggestions(before, n), suggestions(after, n).withColumn("kept", F.lit(1))
    j = a.join(b, ["item", "suggestion"], "left")
    return j.agg(F.count(F.lit(1)).alias("suggestions"), F.round(F.coalesce(F.sum("kept"), F.lit(0)) / F.greatest(F.count(F.lit(1)), F.lit(1)), 6).alias("kept_share"))


def label_utility(recs: DataFrame, labels: DataFrame, features: int = 1 << 12) -> DataFrame:
    """One row: accuracy of a naive Bayes classifier of ``labels(record_id, label)`` on word sets,
    trained on two of three records by hash and tested on the third."""
    from pyspark.ml.classification import NaiveBayes
    from pyspark.ml.feature import HashingTF

    d = HashingTF(inputCol="items", outputCol="features", numFeatures=features, binary=True).transform(recs.join(labels, "record_id").where(F.size("items") > 0)).withColumn("label", F.col("label").cast("double"))
    fold = F.pmod(F.xxhash64("record_id"), F.lit(3))
    d = d.select("features", "label", fold.alias("fold")).persist(StorageLevel.DISK_ONLY)  # read five times; words are not needed any more
    train, test = d.where("fold <> 0"), d.where("fold = 0")
    if not train.head(1) or not test.head(1):
        return recs.sparkSession.createDataFrame([(0, 0.0)], "tested long, accuracy double")
    p = NaiveBayes(modelType="bernoulli").fit(train).transform(test)
    return p.agg(F.count(F.lit(1)).alias("tested"), F.round(F.avg((F.col("prediction") == F.col("label")).cast("double")), 6).alias("accuracy"))
