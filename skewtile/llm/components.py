"""Connected components of an edge table by rounds of joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.llm.scratch import drop_settled, settle


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """edges: (u, v) longs, in any direction. Returns (node, component): each node's smallest reachable node, for all
    nodes that have an edge to another one. Rounds of two star steps: hang every node's larger neighbours on its smallest, then
    its smaller ones; a node's neighbours are only ever aggregated, never gathered."""
    e = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct()
    e = settle(e, "edges")
    before = _state(e)
    while before[0]:
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy(F.col("u").alias("_u")).agg(F.min("v").alias("_m")).select("_u", F.least("_u", "_m").alias("_m"))
        large = both.join(least, F.col("u") == F.col("_u")).where("v > u").select(F.col("v").alias("u"), F.col("_m").alias("v")).distinct()
        least = large.groupBy(F.col("u").alias("_u")).agg(F.min("v").alias("_m"))
        small = large.join(least, F.col("u") == F.col("_u")).select(F.col("v").alias("u"), F.col("_m").alias("v")).where("u <> v")
        small = small.unionByName(least.select(F.col("_u").alias("u"), F.col("_m").alias("v"))).distinct()
        new = settle(small, "edges")
        after = _state(new)
        drop_settled(e)
        e = new
        if after == before:
            break
        before = after
    return e.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
