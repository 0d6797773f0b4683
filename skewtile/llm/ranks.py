"""Gapless ranks and running sums over a total order without a window over a whole table.

Rows are range-partitioned and sorted once; the written table keeps each row's partition and place,
and one small row per partition and group carries the sums before it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from skewtile.llm.scratch import settle


def ranked(df: DataFrame, group: str, order: list[str | Column], rank: str, weight: str | None = None, before: str | None = None) -> DataFrame:
    """df with `rank`, from 0 within each value of `group` in the order given. With `weight`, `before` gets the sum of
    the weights of the group's earlier rows. Equal rows get ranks in any order. Null is a group."""
    placed = df.repartitionByRange(F.col(group), *(F.col(o) if isinstance(o, str) else o for o in order)).sortWithinPartitions(group, *order)
    placed = settle(placed.withColumn("_at", F.monotonically_increasing_id()), "ranked")
    part = F.shiftright("_at", 33)
    sums = [F.count(F.lit(1)).alias("_n"), F.min("_at").alias("_first")] + ([F.sum(weight).alias("_w")] if weight else [])
    parts = placed.groupBy(F.col(group).alias("_group"), part.alias("_of")).agg(*sums)
    ahead = Window.partitionBy("_group").orderBy("_of").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.withColumn("_ahead", F.coalesce(F.sum("_n").over(ahead), F.lit(0)))
    if weight:
        parts = parts.withColumn("_w_ahead", F.coalesce(F.sum("_w").over(ahead), F.lit(0)))
    parts = parts.drop("_n", "_w")
    out = placed.withColumn("_part", part).join(parts, F.col(group).eqNullSafe(F.col("_group")) & (F.col("_part") == F.col("_of")))
    out = out.withColumn(rank, F.col("_ahead") + F.col("_at") - F.col("_first"))
    if weight:
        inside = Window.partitionBy(group, "_part").orderBy("_at").rowsBetween(Window.unboundedPreceding, -1)
        out = out.withColumn(before, F.col("_w_ahead") + F.coalesce(F.sum(weight).over(inside), F.lit(0)))
    return out.select(*df.columns, rank, *([before] if weight else []))
