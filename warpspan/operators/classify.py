"""Nearest-neighbour classification under time warping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from warpspan.operators import search


def classify(test: DataFrame, train: DataFrame, w: int | None, p: float = 1, k: int = 1, method: str = "scan_pass2", leave_one_out: bool = False) -> DataFrame:
    """``query_id, predicted``: the most frequent label of the k nearest; of ties the smallest label.

    With ``leave_one_out`` a series is never its own neighbour.
    """
    queries = test.select(F.col("series_id").alias("query_id"), F.col("v").alias("y"))
    near = search.nearest(queries, train, w, p, k, method, exclude_self=leave_one_out)
    labels = train.select("series_id", "label")
    votes = near.join(labels, "series_id").groupBy("query_id", "label").agg(F.count("*").alias("votes"))
    first = F.min(F.struct((-F.col("votes")).alias("v"), "label"))
    return votes.groupBy("query_id").agg(first.alias("b")).select("query_id", F.col("b.label").alias("predicted"))


def compared(predicted: DataFrame, test: DataFrame) -> DataFrame:
    return predicted.join(test.select(F.col("series_id").alias("query_id"), "label"), "query_id")


def accuracy(predicted: DataFrame, test: DataFrame) -> DataFrame:
    both = compared(predicted, test)
    right = F.sum((F.col("label") == F.col("predicted")).cast("long"))
    return both.agg(F.count("*").alias("items"), right.alias("right"))


def confusion(predicted: DataFrame, test: DataFrame) -> DataFrame:
    """``label, predicted, items``; ``confusion_table`` has it as a matrix."""
    return compared(predicted, test).groupBy("label", "predicted").agg(F.count("*").alias("items"))


def confusion_table(predicted: DataFrame, test: DataFrame) -> DataFrame:
    return compared(predicted, test).groupBy("label").pivot("predicted").count().na.fill(0)
