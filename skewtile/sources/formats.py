"""Points and queries in and out of files; scratch folders for round trips lie where the cluster says."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL: list[str] = []
RECT_SCHEMA = "qid long, x1 double, y1 double, x2 double, y2 double"


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder: spark.checkpoint.dir, else the warehouse, else (local mode) a temporary folder."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base is None and not spark.sparkContext.master.startswith("local"):
        base = spark.conf.get("spark.sql.warehouse.dir")
    if base is None:
        if not _LOCAL:
            _LOCAL.append(tempfile.mkdtemp(prefix="skewtile-io-"))
            atexit.register(shutil.rmtree, _LOCAL[0], True)
        base = f"file://{_LOCAL[0]}"
    return f"{base.rstrip('/')}/skewtile-io/{name}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, kind: str, schema: str | None = None) -> DataFrame:
    """Written and read back as csv, json, orc or parquet; text formats get an explicit schema and keep bad rows as nulls."""
    path = scratch(df.sparkSession, kind)
    df.write.format(kind).save(path)
    reader = df.sparkSession.read.schema(schema or df.schema)
    return (reader.option("mode", "PERMISSIVE") if kind in ("csv", "json") else reader).format(kind).load(path)


def tiled_round_trip(df: DataFrame, tiles: list[int]) -> DataFrame:
    """Parquet partitioned by tile, read back with a tile list that prunes folders."""
    path = scratch(df.sparkSession, "tiled")
    df.write.partitionBy("tile").parquet(path)
    return df.sparkSession.read.parquet(path).where(F.col("tile").isin(tiles))


def window_scan(lineitem: DataFrame, x1: float, x2: float) -> DataFrame:
    """Rows of plane L in a band of x, with the band also as a predicate on the stored column, so that row groups are skipped.
    It is a little wider, as x is rounded; the exact one follows."""
    stored = F.col("l_extendedprice").between(x1 / 100 - 0.01, x2 / 100 + 0.01)
    return lineitem.where(stored).where(F.round(F.col("l_extendedprice") * 100).between(x1, x2))
