"""Tiles dealt out to tasks in blocks of bounded size, data before queries, for kernels that stream."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, GroupedData
from pyspark.sql import functions as F

from skewtile.plans.tilemap import by_tile

PART_ROWS = 1 << 18
"""About so many rows of a tile's data are indexed at once."""
SHARE_QUERIES = 1 << 12
"""Where few tiles are asked, a tile's queries are shared out, but not below so many."""
MOST_TASKS = 4096


def dealt(data: DataFrame, routed: DataFrame, counts: np.ndarray, slot: list[str], n_slots: int = 1) -> GroupedData:
    """Data (tile, id, x1, y1, ...) and queries (tile, id, x1, y1, x2, y2, ...) in groups of a part of a tile's data and a share of its
    queries, sorted data first. Each pair meets in one group. One job counts the queries of each tile. With slots, data stay where they lie."""
    spark = data.sparkSession
    asked = np.zeros(len(counts), np.int64)
    for r in routed.groupBy("tile").agg(F.count(F.lit(1)).alias("n")).collect():  # a row a tile
        asked[r["tile"]] = r["n"]
    parts = np.where(asked > 0, np.maximum(1, -(-np.asarray(counts, np.int64) // PART_ROWS)), 1)
    wanted = 4 * spark.sparkContext.defaultParallelism
    spread = -(-wanted // max(1, int(parts[asked > 0].sum())))
    shares = np.clip(-(-asked // SHARE_QUERIES), 1, spread)
    own = lambda n: F.pmod(F.xxhash64("id"), by_tile(n.tolist(), F.col("tile"), "int")).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), by_tile(n.tolist(), F.col("tile"), "int") - 1))
    data = data.withColumns({"part": own(parts), "second": F.lit(False)}).withColumn("share", every(shares))
    routed = routed.withColumns({"share": own(shares), "second": F.lit(True)}).withColumn("part", every(parts))
    keys = [*slot, "tile", "part", "share"]
    groups = int((parts * shares)[asked > 0].sum())
    if slot:
        routed = routed.repartition(n_slots, "slot")
    both = data.unionByName(routed, allowMissingColumns=True)
    if not slot:
        both = both.repartition(max(1, min(2 * groups, MOST_TASKS)), *keys)
    return both.sortWithinPartitions(*keys, "second").groupBy(*keys)


def parts(rows: DataFrame, counts: np.ndarray, key: str, size: int = 1 << 16) -> GroupedData:
    """Rows of tiles in groups of about `size` rows of one tile."""
    n = np.maximum(1, -(-np.asarray(counts, np.int64) // size))
    rows = rows.withColumn("part", F.pmod(F.xxhash64(key), by_tile(n.tolist(), F.col("tile"), "int")))
    return rows.repartition(max(1, min(2 * int(n.sum()), MOST_TASKS)), "tile", "part").groupBy("tile", "part")


def first_side(batches: Iterator[pa.RecordBatch], columns: tuple[str, ...]) -> tuple:
    """The data of a group as arrays, by column, and the batches of queries that follow."""
    held, rest = [], iter(())
    for b in batches:
        n = b.num_rows - int(np.count_nonzero(b.column("second").to_numpy(zero_copy_only=False)))
        if n:
            held.append(b.slice(0, n))
        if n < b.num_rows:
            rest = chain([b.slice(n)], batches)
            break
    return *(np.concatenate([h.column(c).to_numpy(zero_copy_only=False) for h in held]) if held else np.zeros(0) for c in columns), rest
