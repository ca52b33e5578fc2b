"""Prediction on neighbours: vote, mean, weights, accuracy, density."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from orthant.sources.tables import written

EPS = 1e-9


def with_label(neighbors: DataFrame, labels: DataFrame, label: str = "label") -> DataFrame:
    """neighbors and the label of their pid; labels: (pid, label). The optimizer broadcasts small label tables."""
    return neighbors.join(labels.select("pid", F.col(label).alias("label")), "pid")


def classify(neighbors: DataFrame, labels: DataFrame, weights: str = "uniform", label: str = "label") -> DataFrame:
    """(qid, predicted, votes MAP): most votes, then the nearest voter, then the smaller label."""
    weight = {"uniform": F.lit(1.0), "inverse": 1 / (F.col("d2") + EPS)}[weights]
    votes = with_label(neighbors, labels, label).groupBy("qid", "label").agg(F.sum(weight).alias("votes"), F.min("rank").alias("best"))
    ranked = votes.withColumn("place", F.row_number().over(Window.partitionBy("qid").orderBy(F.col("votes").desc(), "best", "label")))
    return ranked.groupBy("qid").agg(F.min(F.when(F.col("place") == 1, F.col("label"))).alias("predicted"), F.map_from_entries(F.sort_array(F.collect_list(F.struct("label", "votes")))).alias("votes"))


def regress(neighbors: DataFrame, targets: DataFrame, target: str = "target", weights: str = "uniform") -> DataFrame:
    """(qid, predicted): mean of the neighbours' targets; plain means add as decimals, so their order can't matter."""
    met = neighbors.join(targets.select("pid", F.col(target).alias("t")), "pid")
    if weights == "uniform":
        return met.groupBy("qid").agg((F.sum(F.col("t").cast("decimal(20,6)")) / F.count(F.lit(1))).cast("double").alias("predicted"))
    w = 1 / (F.col("d2") + EPS)
    return met.groupBy("qid").agg((F.sum(w * F.col("t")) / F.sum(w)).alias("predicted"))


def judged(predictions: DataFrame, truth: DataFrame, label: str = "label") -> DataFrame:
    return predictions.join(truth.select(F.col("pid").alias("qid"), F.col(label).alias("truth")), "qid")


def accuracy(predictions: DataFrame, truth: DataFrame, label: str = "label") -> DataFrame:
    met = judged(predictions, truth, label)
    return met.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("predicted") == F.col("truth")).cast("long")).alias("hits")).select("n", "hits", F.round(F.col("hits") / F.col("n"), 6).alias("accuracy"))


def confusion(predictions: DataFrame, truth: DataFrame, label: str = "label") -> DataFrame:
    """Counts by truth and prediction, with totals of each truth and of all."""
    return judged(predictions, truth, label).rollup("truth", "predicted").agg(F.count(F.lit(1)).alias("n"))


def class_recall(predictions: DataFrame, truth: DataFrame, label: str = "label") -> DataFrame:
    met = judged(predictions, truth, label)
    return met.groupBy("truth").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("predicted") == F.col("truth")).cast("double")), 6).alias("recall"))


def knn_density(neighbors: DataFrame, k: int, dims: int, dense_above: float | None = None) -> DataFrame:
    """(qid, d2_k, density): k over the volume of the ball that reaches the k-th neighbour; infinite in a spot of k points.

    dense_above: also dense, whether the density exceeds it.
    """
    ball = math.pi ** (dims / 2) / math.gamma(dims / 2 + 1)
    volume = F.lit(ball) * F.pow("d2", F.lit(dims / 2))
    told = neighbors.where(F.col("rank") == k).select("qid", F.col("d2").alias("d2_k"), F.when(F.col("d2") > 0, F.lit(float(k)) / volume).otherwise(F.lit(float("inf"))).alias("density"))
    return told if dense_above is None else told.withColumn("dense", F.col("density") > F.lit(float(dense_above)))


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """Share of the exact neighbours that were found, and the worst ratio of k-th distances (1 where both are 0)."""
    found, exact = (written(df.select("qid", "pid", "dist"), name) for df, name in ((found, "found"), (exact, "exact")))  # each is looked at twice
    hits = exact.select("qid", "pid").join(found.select("qid", "pid", F.lit(1).alias("hit")), ["qid", "pid"], "left").agg(F.count(F.lit(1)).alias("n"), F.sum(F.coalesce("hit", F.lit(0))).alias("found"))
    far = lambda df, c: df.groupBy("qid").agg(F.max("dist").alias(c))
    ratio = F.when(F.col("b") == F.col("a"), F.lit(1.0)).otherwise(F.col("b") / F.col("a"))
    worst = far(exact, "a").join(far(found, "b"), "qid", "left").agg(F.round(F.max(F.coalesce(ratio, F.lit(float("inf")))), 6).alias("worst_ratio"))
    return hits.crossJoin(worst).select("n", "found", F.round(F.col("found") / F.col("n"), 6).alias("recall"), "worst_ratio")  # one row each
