"""Merging of local answers."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def union(parts: list[DataFrame]) -> DataFrame:
    """Range answers: a point has one tile, so nothing is there twice and nothing is shuffled."""
    return reduce(DataFrame.unionByName, parts)


def topk(candidates: DataFrame, k: int | Column) -> DataFrame:
    """The k first candidates of each query, ties by pid, x, y. With a constant k, Spark keeps k a task before the shuffle."""
    order = Window.partitionBy("qid").orderBy("dist2", "pid", "x", "y")
    ranked = candidates.withColumn("rank", F.row_number().over(order))
    return ranked.where(F.col("rank") <= k).select("qid", "pid", "dist2", "rank")
