"""Tasks on top of nearest neighbours: classification, outliers, softmax."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .plans.storage import written


def knn_classify(answers: DataFrame, labels: DataFrame, label: str = "label") -> DataFrame:
    """(query_id, predicted, votes): the most frequent label of the neighbours; ties to the least label."""
    votes = answers.join(labels.select("series_id", F.col(label).alias("label")), "series_id").groupBy("query_id", "label").agg(F.count(F.lit(1)).alias("votes"))
    order = Window.partitionBy("query_id").orderBy(F.desc("votes"), "label")
    return votes.withColumn("i", F.row_number().over(order)).where("i = 1").select("query_id", F.col("label").alias("predicted"), "votes")


def knn_outliers(answers: DataFrame, k: int) -> DataFrame:
    """(query_id, score): distance to the k-th neighbour, or to the farthest that was found."""
    return answers.where(F.col("rank") <= k).groupBy("query_id").agg(F.max("distance").alias("score"))


def roc_auc(scored: DataFrame, score: str, positive: str) -> float:
    """Share of (positive, negative) pairs in right order, by the rank formula; ties count half.

    Distinct scores are range-partitioned; negatives below a score are those of the
    partitions before it (one row a partition) and of its own partition.
    """
    by = scored.groupBy(score).agg(F.sum(F.col(positive).cast("long")).alias("p"), F.sum((~F.col(positive)).cast("long")).alias("q"))
    parts = written(by.repartitionByRange(score).withColumn("part", F.spark_partition_id()), "scores")
    ahead = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row a partition
    before = parts.groupBy("part").agg(F.sum("q").alias("all")).withColumn("ahead", F.coalesce(F.sum("all").over(ahead), F.lit(0))).select("part", "ahead")
    inside = Window.partitionBy("part").orderBy(score).rowsBetween(Window.unboundedPreceding, -1)
    below = F.coalesce(F.sum("q").over(inside), F.lit(0)) + F.col("ahead")
    row = parts.join(F.broadcast(before), "part").withColumn("below", below).agg(F.sum(F.col("p") * (F.col("below") + F.col("q") / 2)).alias("u"), F.sum("p").alias("p"), F.sum("q").alias("q")).first()
    return float(row["u"] / (row["p"] * row["q"])) if row["p"] and row["q"] else float("nan")


def knn_softmax(answers: DataFrame, temperature: float = 1.0) -> DataFrame:
    """(query_id, series_id, weight): softmax of inner products over the neighbours found.

    On unit vectors the inner product is 1 - distance ^ 2 / 2, so distances suffice.
    """
    score = F.exp((1 - F.col("distance") * F.col("distance") / 2) / temperature)
    return answers.withColumn("e", score).withColumn("weight", F.col("e") / F.sum("e").over(Window.partitionBy("query_id"))).select("query_id", "series_id", "weight")
