"""Streams over event files, run to their end and returned as tables; and the batch loop that plans and learns as it goes."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewtile.operators.rangejoin import adapt, range_join
from skewtile.operators.tiled import TiledTable
from skewtile.plans import planner, route
from skewtile.sources.formats import scratch
from skewtile.sources.planes import AREAS

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, sf_dir: str, max_files: int = 1) -> DataFrame:
    """The events file as a stream of plane E rows with a timestamp that watermarks take."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", max_files).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    seconds = F.timestamp_diff("SECOND", F.lit("2024-01-01 00:00:00").cast("timestamp_ntz"), F.col("ts"))
    return raw.select(F.col("event_id").alias("pid"), seconds.cast("double").alias("x"), (F.round(F.col("value") * 100) * 50).alias("y"), "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))


def area_label() -> F.Column:
    out = F.lit("rest")
    for name, (x1, y1, x2, y2) in AREAS.items():
        out = F.when(F.col("x").between(x1, x2) & F.col("y").between(y1, y2), F.lit(name)).otherwise(out)
    return out


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there and returns its output. Append goes to a Parquet sink, whose log takes each batch once; complete
    and update keep the latest rows in a table that every batch writes anew."""
    spark = stream.sparkSession
    out, log = scratch(spark, "sink"), scratch(spark, "log")
    if mode == "append":
        query = stream.writeStream.format("parquet").option("checkpointLocation", log).option("path", out).outputMode("append").trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{number}")

    query = stream.writeStream.foreachBatch(put).option("checkpointLocation", log).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    last = max((p["batchId"] for p in query.recentProgress), default=0)
    return spark.read.schema(stream.schema).parquet(f"{out}/{last}")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = read_events(spark, sf_dir).withWatermark("ts", "1 hour").withColumn("area", area_label())
    counts = counts.groupBy(F.window("ts", "1 hour"), "area").agg(F.count(F.lit(1)).alias("n"))
    return drain(counts.select(F.col("window.start").alias("start"), "area", "n"), "complete").select(F.col("start").cast("timestamp_ntz"), "area", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = read_events(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour", "15 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return drain(counts.select(F.col("window.start").alias("start"), "n"), "complete").select(F.col("start").cast("timestamp_ntz"), "n")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = read_events(spark, sf_dir).withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", "10 minutes"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return drain(counts.select("user_id", F.col("session_window.start").alias("start"), "n"), "complete").select("user_id", F.col("start").cast("timestamp_ntz"), "n")


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts under a watermark. All rows of the table come in one batch, so none is behind it; late_example has rows that are."""
    counts = read_events(spark, sf_dir).withWatermark("ts", "1 minute").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return drain(counts.select(F.col("window.start").alias("start"), "n"), "complete").select(F.col("start").cast("timestamp_ntz"), "n")


def late_example(spark: SparkSession) -> DataFrame:
    """Hourly counts (start, n) of five batches under a watermark of an hour: the fourth one's row from the first hour comes when that hour is
    closed, and is dropped; its other row counts. Late is what was behind the watermark of the batch before."""
    folder = scratch(spark, "late")
    rows = [["2024-01-01 00:10:00", "2024-01-01 00:50:00"], ["2024-01-01 05:10:00"], ["2024-01-01 06:20:00"], ["2024-01-01 00:30:00", "2024-01-01 06:40:00"], ["2024-01-01 09:00:00"]]
    for i, batch in enumerate(rows):
        spark.createDataFrame([(t,) for t in batch], "ts string").select(F.col("ts").cast("timestamp").alias("ts")).coalesce(1).write.mode("append").parquet(f"{folder}/batch={i}")
        time.sleep(0.05)  # files are taken in the order of their times
    stream = spark.readStream.schema("ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{folder}/batch=*")
    counts = stream.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return drain(counts.select(F.col("window.start").alias("start"), "n"), "append").select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events read twice, one left of each."""
    both = read_events(spark, sf_dir).union(read_events(spark, sf_dir)).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["pid"])
    return drain(both.select("pid", "x", "y"))


def static_join(spark: SparkSession, sf_dir: str, tt: TiledTable, half: float = 20000.0, every: int = 50) -> DataFrame:
    """Windows that arrive as a stream, joined with a standing tiled table: (qid, pid)."""
    e = read_events(spark, sf_dir).where(F.col("pid") % every == 0)
    w = e.select(F.col("pid").alias("qid"), (F.col("x") - half).alias("x1"), (F.col("y") - half).alias("y1"), (F.col("x") + half).alias("x2"), (F.col("y") + half).alias("y2"))
    side = F.lit(2 * half)
    cells = route.ranges(w, tt.tiles).withColumn("cx", F.explode(F.sequence(F.floor(F.col("x1") / side), F.floor(F.col("x2") / side))))
    cells = cells.withColumn("cy", F.explode(F.sequence(F.floor(F.col("y1") / side), F.floor(F.col("y2") / side))))
    data = tt.rows.select("pid", "x", "y", "tile", F.floor(F.col("x") / side).alias("cx"), F.floor(F.col("y") / side).alias("cy"))
    inside = F.col("x").between(F.col("x1"), F.col("x2")) & F.col("y").between(F.col("y1"), F.col("y2"))
    return drain(cells.join(data, ["tile", "cx", "cy"]).where(inside).select("qid", "pid"))


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of a purchase and a click of one user up to an hour before it."""
    e = read_events(spark, sf_dir).withWatermark("ts", "2 hours")
    a = e.where("event_type = 'purchase'").select(F.col("pid").alias("buy"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    b = read_events(spark, sf_dir).withWatermark("ts", "2 hours").where("event_type = 'click'").select(F.col("pid").alias("click"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return drain(a.join(b, F.expr("u1 = u2 AND t2 <= t1 AND t2 >= t1 - INTERVAL 1 HOUR")).select("buy", "click"))


def stateful_load(spark: SparkSession, sf_dir: str, tt: TiledTable) -> DataFrame:
    """Events per tile, kept as state: (tile, n), the last row of each tile being its load."""
    e = read_events(spark, sf_dir).withColumn("tile", tt.tiles.tile_of(F.col("x"), F.col("y")))

    def count(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"tile": [key[0]], "n": [n]})

    counted = e.select("tile", "pid").groupBy("tile").applyInPandasWithState(count, "tile int, n long", "n long", "update", "NoTimeout")
    return drain(counted, "update")


@dataclass
class BatchLoop:
    """Batches of windows against a standing tiled table. Batch n uses filter version n and learns version n + 1; a tile map is
    planned anew when the queries have drifted. Batches are known by number, so one that is replayed after a failure uses what it used before."""

    table: TiledTable
    sink: Callable[[DataFrame, int], None]
    budget: int = 8
    learn: bool = True
    routed: list[int] = field(default_factory=list)
    replanned: list[int] = field(default_factory=list)
    _versions: dict[int, TiledTable] = field(default_factory=dict)
    _load: np.ndarray | None = None

    def __call__(self, batch: DataFrame, number: int) -> None:
        tt = self._versions.setdefault(number, self.table)
        windows = batch.select("qid", "x1", "y1", "x2", "y2").persist()
        seen = {r["tile"]: r["n"] for r in route.ranges(windows, tt.tiles, tt.filters).groupBy("tile").agg(F.count(F.lit(1)).alias("n")).collect()}
        load = np.array([seen.get(t, 0) for t in range(tt.tiles.n_tiles)])
        self.routed.append(int(load.sum()))
        drift = self._load is not None and len(self._load) == len(load) and planner.should_replan(self._load, load)
        if drift:
            self.replanned.append(number)
        self.sink(range_join(windows, tt, filter=tt.filters is not None, plan="query" if drift else None, budget=self.budget), number)
        if self.learn:
            self.table = adapt(windows, tt)
            self._versions[number + 1] = self.table
        self._load = load
        windows.unpersist()


def query_files(spark: SparkSession, folder: str) -> DataFrame:
    return spark.readStream.schema("qid long, x1 double, y1 double, x2 double, y2 double").option("maxFilesPerTrigger", 1).parquet(folder)


def run_loop(stream: DataFrame, loop: BatchLoop) -> None:
    log = scratch(stream.sparkSession, "loop")
    stream.writeStream.foreachBatch(loop).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()


