"""The methods from SQL: a tiled table becomes a view with routing functions of its own, so joins are written as SQL text."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from skewtile.functions.geometry import np_maxdist2
from skewtile.operators import knnjoin, rangejoin
from skewtile.operators.tiled import TiledTable


class _QuadCover:
    """quad_cover(x1, y1, x2, y2, side): the cells (gx, gy) that a window covers."""

    def eval(self, x1: float, y1: float, x2: float, y2: float, side: float):
        for gx in range(math.floor(x1 / side), math.floor(x2 / side) + 1):
            for gy in range(math.floor(y1 / side), math.floor(y2 / side) + 1):
                yield gx, gy


def register(spark: SparkSession) -> None:
    spark.udtf.register("quad_cover", udtf(_QuadCover, returnType="gx: bigint, gy: bigint"))


def register_table(spark: SparkSession, name: str, tt: TiledTable) -> None:
    """View `name` of the rows with their tile, and functions: name_tile(x, y); name_tiles(x1, y1, x2, y2), the tiles whose data a window may meet;
    name_reach(x, y, k), a radius within which k points lie for sure (infinite where there are fewer)."""
    tt.rows.createOrReplaceTempView(name)
    locate, meet = tt.tiles.locate, tt.tiles.rect_tiles
    boxes, counts = tt.tiles.mbr[tt.counts > 0], tt.counts[tt.counts > 0]

    @F.pandas_udf("int")
    def tile(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series(locate(x.to_numpy(), y.to_numpy()).astype("int32"))

    @F.pandas_udf("array<int>")
    def tiles(x1: pd.Series, y1: pd.Series, x2: pd.Series, y2: pd.Series) -> pd.Series:
        return pd.Series(meet(np.column_stack([x1, y1, x2, y2])))

    @F.pandas_udf("double")
    def reach(x: pd.Series, y: pd.Series, k: pd.Series) -> pd.Series:
        out = np.full(len(x), np.inf)
        for i, (a, b, n) in enumerate(zip(x, y, k)):
            d = np_maxdist2(np.array([a]), np.array([b]), boxes)[0] if len(boxes) else np.zeros(0)
            order = np.argsort(d, kind="stable")
            enough = np.flatnonzero(np.cumsum(counts[order]) >= n)
            if len(enough):
                out[i] = math.sqrt(d[order[enough[0]]]) * (1 + 1e-12)
        return pd.Series(out)

    for suffix, f in (("tile", tile), ("tiles", tiles), ("reach", reach)):
        spark.udf.register(f"{name}_{suffix}", f)


def _cell_views(q: DataFrame, tt: TiledTable, name: str) -> None:
    """Views name_windows_cells and name_cells: both sides with the cells (tile, level, _cx, _cy) that they meet in."""
    cells = rangejoin.Cells.of(q, tt.tiles)
    d, w, _ = rangejoin.cell_keyed(tt.rows.select("pid", "x", "y", "tile"), q, cells, tt.tiles)
    d.createOrReplaceTempView(f"{name}_cells")
    w.createOrReplaceTempView(f"{name}_windows_cells")


_MEET = "d.tile = w.tile AND d.level = w.level AND d._cx = w._cx AND d._cy = w._cy AND d.x BETWEEN w.x1 AND w.x2 AND d.y BETWEEN w.y1 AND w.y2"


def range_join(spark: SparkSession, q: DataFrame, tt: TiledTable, name: str = "tiled_points") -> DataFrame:
    """The range join as SQL over the registered table: (qid, pid)."""
    register_table(spark, name, tt)
    q.createOrReplaceTempView(f"{name}_windows")
    _cell_views(spark.sql(f"SELECT *, explode({name}_tiles(x1, y1, x2, y2)) AS tile FROM {name}_windows WHERE x1 <= x2 AND y1 <= y2"), tt, name)
    return spark.sql(f"SELECT w.qid, d.pid FROM {name}_windows_cells w JOIN {name}_cells d ON {_MEET}")


def knn(spark: SparkSession, q: DataFrame, tt: TiledTable, k: int, name: str = "tiled_points") -> DataFrame:
    """The nearest-neighbour join as SQL over the registered table: (qid, pid, rank)."""
    register_table(spark, name, tt)
    knnjoin.cell_bound(q, tt, F.lit(k)).createOrReplaceTempView(f"{name}_focal")
    x1, y1, x2, y2 = tt.frame
    routed = spark.sql(f"""
        WITH r AS (SELECT qid, cx, cy, least({name}_reach(cx, cy, {k:d}), coalesce(sqrt(cell_r2) * (1 + 1e-12), double('infinity'))) AS r FROM {name}_focal),
        b AS (SELECT *, greatest(cx - r, {x1!r}D) AS x1, greatest(cy - r, {y1!r}D) AS y1, least(cx + r, {x2!r}D) AS x2, least(cy + r, {y2!r}D) AS y2 FROM r)
        SELECT *, explode({name}_tiles(x1, y1, x2, y2)) AS tile FROM b""")
    _cell_views(routed, tt, name)
    return spark.sql(f"""
        WITH c AS (SELECT w.qid, d.pid, d.x, d.y, (d.x - cx) * (d.x - cx) + (d.y - cy) * (d.y - cy) AS dist2 FROM {name}_windows_cells w JOIN {name}_cells d ON {_MEET}),
        n AS (SELECT qid, pid, row_number() OVER (PARTITION BY qid ORDER BY dist2, pid, x, y) AS rank FROM c)
        SELECT qid, pid, rank FROM n WHERE rank <= {k:d}""")
