"""Queries as a Python data source: uniform or around hot spots, the same for a seed, in any number of partitions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_SCHEMA = "qid long, cx double, cy double"


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__((first, last))


class _Reader(DataSourceReader):
    """Options: n, seed, x1, y1, x2, y2, hot (share of queries around the middle of the box), spread, partitions."""

    def __init__(self, options: dict):
        self.n, self.seed = int(options.get("n", 1000)), int(options.get("seed", 1))
        self.box = [float(options.get(k, d)) for k, d in (("x1", 0), ("y1", 0), ("x2", 1), ("y2", 1))]
        self.hot, self.spread = float(options.get("hot", 0)), float(options.get("spread", 0.02))
        self.parts = int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        at = np.linspace(0, self.n, self.parts + 1).astype(int)
        return [_Range(int(a), int(b)) for a, b in zip(at, at[1:])]

    def read(self, partition) -> Iterator[pa.RecordBatch]:
        first, last = partition.value
        x1, y1, x2, y2 = self.box
        for a in range(first, last, 4096):  # the numbers depend on the block of qids, not on the partition
            ids = np.arange(a, min(last, a + 4096))
            u = np.array([np.random.default_rng([self.seed, i]).random(5) for i in ids])
            near = u[:, 4] < self.hot
            fx = np.where(near, np.clip(0.5 + self.spread * (2 * u[:, 2] - 1), 0, 1), u[:, 0])
            fy = np.where(near, np.clip(0.5 + self.spread * (2 * u[:, 3] - 1), 0, 1), u[:, 1])
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(x1 + fx * (x2 - x1)), pa.array(y1 + fy * (y2 - y1))], ["qid", "cx", "cy"])


class QueryGenerator(DataSource):
    @classmethod
    def name(cls) -> str:
        return "spatial_queries"

    def schema(self) -> str:
        return _SCHEMA

    def reader(self, schema) -> _Reader:
        return _Reader(self.options)


def generated(spark, **options):
    spark.dataSource.register(QueryGenerator)
    return spark.read.format("spatial_queries").options(**{k: str(v) for k, v in options.items()}).load()


def generated_from(points: DataFrame, hot: int = 2, spread: float = 0.02) -> DataFrame:
    """A query (qid, cx, cy) for each point of a table, in the box of its points: uniform, but every hot-th around the middle. The numbers come
    from the point's id alone."""
    box = points.agg(F.min("x").alias("x1"), F.min("y").alias("y1"), F.max("x").alias("x2"), F.max("y").alias("y2"))
    share = lambda a, m: (F.col("pid") * a % m).cast("double") / m
    place = lambda u: F.when(F.col("pid") % hot == 0, 0.5 + spread * (2 * u - 1)).otherwise(u)
    at = lambda lo, hi, u: F.col(lo) + place(u) * (F.col(hi) - F.col(lo))
    return points.crossJoin(F.broadcast(box)).select(F.col("pid").alias("qid"), at("x1", "x2", share(7919, 10007)).alias("cx"), at("y1", "y2", share(6271, 9973)).alias("cy"))


def generated_sql(plane: str, hot: int = 2, spread: float = 0.02) -> str:
    u = lambda a, m: f"(CAST(pid * {a} % {m} AS DOUBLE) / {m})"
    place = lambda v: f"(CASE WHEN pid % {hot} = 0 THEN 0.5e0 + {spread}e0 * (2 * {v} - 1) ELSE {v} END)"
    box = f"(SELECT min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM {plane})"
    return f"SELECT pid AS qid, x1 + {place(u(7919, 10007))} * (x2 - x1) AS cx, y1 + {place(u(6271, 9973))} * (y2 - y1) AS cy FROM {plane} CROSS JOIN {box}"
