"""Planes: exact integer-valued projections of the given tables to points (pid, x, y), with the same in DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_ORIGIN_TS, _ORIGIN_DAY = "2024-01-01 00:00:00", "1995-01-01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _days(column: str):
    return F.datediff(F.col(column), F.lit(_ORIGIN_DAY).cast("date"))


def events(spark: SparkSession, sf_dir: str, *payload: str) -> DataFrame:
    t = table(spark, sf_dir, "events")
    seconds = F.timestamp_diff("SECOND", F.lit(_ORIGIN_TS).cast("timestamp_ntz"), F.col("ts"))
    return t.select(F.col("event_id").alias("pid"), seconds.cast("double").alias("x"), (F.round(F.col("value") * 100) * 50).alias("y"), *payload)


def lineitem(spark: SparkSession, sf_dir: str, *payload: str) -> DataFrame:
    t = table(spark, sf_dir, "lineitem")
    pid = ((F.col("l_orderkey") * 1000000 + F.col("l_partkey")) * 10000 + F.col("l_suppkey")) * 8 + F.col("l_linenumber")
    return t.select(pid.alias("pid"), F.round(F.col("l_extendedprice") * 100).alias("x"), (_days("l_shipdate") * 4200).cast("double").alias("y"), *payload)


def orders(spark: SparkSession, sf_dir: str, *payload: str) -> DataFrame:
    t = table(spark, sf_dir, "orders")
    return t.select(F.col("o_orderkey").alias("pid"), F.round(F.col("o_totalprice") * 100).alias("x"), (_days("o_orderdate") * 20000).cast("double").alias("y"), *payload)


def embeddings(spark: SparkSession, sf_dir: str, *payload: str) -> DataFrame:
    at = lambda i: F.round(F.get("embedding", i).cast("double") * 1000000)
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("pid"), at(0).alias("x"), at(1).alias("y"), *payload)


def documents(spark: SparkSession, sf_dir: str, *payload: str) -> DataFrame:
    t = table(spark, sf_dir, "documents")
    return t.select(F.col("doc_id").alias("pid"), (F.col("n_chars") * 100).cast("double").alias("x"), (F.col("doc_id") * 7919 % 10007 * 100).cast("double").alias("y"), *payload)


def customers(spark: SparkSession, sf_dir: str, *payload: str) -> DataFrame:
    t = table(spark, sf_dir, "customer")
    return t.select(F.col("c_custkey").alias("pid"), F.round((F.col("c_acctbal") + 1000) * 100).alias("x"), (F.col("c_nationkey") * 40000).cast("double").alias("y"), *payload)


PLANES = {"E": events, "L": lineitem, "O": orders, "V": embeddings, "N": documents, "C": customers}

SQL = {
    "E": "(SELECT event_id AS pid, CAST(floor(epoch(ts) - epoch(TIMESTAMP '2024-01-01 00:00:00')) AS DOUBLE) AS x, round(value * 100) * 50 AS y, user_id, event_type, ts, value, props FROM events)",
    "L": "(SELECT ((l_orderkey * 1000000 + l_partkey) * 10000 + l_suppkey) * 8 + l_linenumber AS pid, round(l_extendedprice * 100) AS x, CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) * 4200 AS DOUBLE) AS y, l_orderkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_returnflag, l_shipdate FROM lineitem)",
    "O": "(SELECT o_orderkey AS pid, round(o_totalprice * 100) AS x, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) * 20000 AS DOUBLE) AS y, o_custkey, o_orderstatus FROM orders)",
    "V": "(SELECT vec_id AS pid, round(CAST(embedding[1] AS DOUBLE) * 1000000) AS x, round(CAST(embedding[2] AS DOUBLE) * 1000000) AS y FROM embeddings)",
    "N": "(SELECT doc_id AS pid, CAST(n_chars * 100 AS DOUBLE) AS x, CAST(doc_id * 7919 % 10007 * 100 AS DOUBLE) AS y FROM documents)",
    "C": "(SELECT c_custkey AS pid, round((c_acctbal + 1000) * 100) AS x, CAST(c_nationkey * 40000 AS DOUBLE) AS y FROM customer)",
}

AREAS = {"a": (600000.0, 0.0, 900000.0, 300000.0), "b": (1500000.0, 0.0, 1700000.0, 200000.0), "c": (2200000.0, 400000.0, 2400000.0, 900000.0)}
"""Boxes of plane E that stand for hot places."""


def windows_of(points: DataFrame, half: float, every: int, area: str | None = None) -> DataFrame:
    """Rectangle queries around every so-manieth point, of one area or all: (qid, x1, y1, x2, y2)."""
    p = points.where(F.col("pid") % every == 0)
    if area:
        x1, y1, x2, y2 = AREAS[area]
        p = p.where(F.col("x").between(x1, x2) & F.col("y").between(y1, y2))
    return p.select(F.col("pid").alias("qid"), (F.col("x") - half).alias("x1"), (F.col("y") - half).alias("y1"), (F.col("x") + half).alias("x2"), (F.col("y") + half).alias("y2"))


def windows_sql(plane: str, half: float, every: int, area: str | None = None, scale: str = "") -> str:
    where = f"pid % {every} = 0"
    if area:
        x1, y1, x2, y2 = AREAS[area]
        where += f" AND x BETWEEN {x1:.0f} AND {x2:.0f} AND y BETWEEN {y1:.0f} AND {y2:.0f}"
    return f"(SELECT pid AS qid, x{scale} - {half:.0f} AS x1, y{scale} - {half:.0f} AS y1, x{scale} + {half:.0f} AS x2, y{scale} + {half:.0f} AS y2 FROM {SQL[plane]} WHERE {where})"


def focal_points(points: DataFrame, every: int) -> DataFrame:
    return points.where(F.col("pid") % every == 0).select(F.col("pid").alias("qid"), F.col("x").alias("cx"), F.col("y").alias("cy"))
