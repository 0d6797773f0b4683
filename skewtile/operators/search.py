"""Searches for one query at a time: windows, discs, polygons, nearest neighbours."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skewtile.functions import geometry as g
from skewtile.operators.tiled import TiledTable
from skewtile.plans import obf

Rect = tuple[float, float, float, float]
Circle = tuple[float, float, float]


def tiles_for(tt: TiledTable, shape: Rect | Circle) -> list[int]:
    """Tiles that may hold something of the shape: their data's box meets it, and their filter, if any, says so."""
    b = tt.tiles.data_boxes()
    if len(shape) == 4:
        hit = g.rects_meet(*shape, b[:, 0], b[:, 1], b[:, 2], b[:, 3])
    else:
        hit = g.np_mindist2(np.array([shape[0]]), np.array([shape[1]]), b)[0] <= shape[2] ** 2
    found = [int(t) for t in np.flatnonzero(hit)]
    if tt.filters is not None:
        found = [t for t in found if t in tt.filters.filters and obf.may_contain(tt.filters.filters[t], shape)]
    return found


def range_search(tt: TiledTable, shape: Rect | Circle, keyword: str | None = None, text: str = "text", where: Column | None = None, texts: DataFrame | None = None) -> DataFrame:
    """The points of a closed window or disc: a tile list for partition pruning, then the predicate, then a text predicate. texts: a table of
    one key column and the text, where the points carry only the key."""
    x, y = F.col("x"), F.col("y")
    inside = g.in_rect(x, y, *map(F.lit, shape)) if len(shape) == 4 else g.in_circle(x, y, *map(F.lit, shape))
    df = tt.rows.where(F.col("tile").isin(tiles_for(tt, shape))).where(inside)
    if keyword is not None:
        has = F.array_contains(F.split(F.lower(F.col(text)), "[^a-z0-9]+"), keyword.lower())
        if texts is None:
            df = df.where(has)
        else:
            key = next(c for c in texts.columns if c != text)
            df = df.join(texts.where(has).select(key), key, "left_semi")
    return df if where is None else df.where(where)


def polygon_search(tt: TiledTable, ring: Sequence[tuple[float, float]]) -> DataFrame:
    """The points of a simple polygon, border included: its box first, then crossings counted in Columns."""
    xs, ys = zip(*ring)
    near = range_search(tt, (min(xs), min(ys), max(xs), max(ys)))
    x, y = F.col("x"), F.col("y")
    odd, border = F.lit(0), F.lit(False)
    for (ax, ay), (bx, by) in zip(ring, [*ring[1:], ring[0]]):
        turn = (bx - ax) * (y - ay) - (by - ay) * (x - ax)
        border = border | ((turn == 0) & x.between(min(ax, bx), max(ax, bx)) & y.between(min(ay, by), max(ay, by)))
        if ay != by:
            crosses = ((F.lit(ay) > y) != (F.lit(by) > y)) & (x < (bx - ax) * (y - ay) / (by - ay) + ax)
            odd = odd + crosses.cast("int")
    return near.where(border | (odd % 2 == 1))


def knn_search(tt: TiledTable, x: float, y: float, k: int, where: Column | None = None) -> DataFrame:
    """(pid, x, y, dist2, rank) of the k nearest points, ties by pid, x, y. The radius comes from the tiles' boxes and counts, so one
    round over the tiles within it is enough; with a predicate, counts are those of the rows that pass it."""
    d2 = g.dist2(F.col("x"), F.col("y"), F.lit(float(x)), F.lit(float(y)))
    df, counts = tt.rows, tt.counts
    if where is not None:
        df = df.where(where)
        counts = np.zeros_like(counts)
        for r in df.groupBy("tile").count().collect():  # a row a tile
            counts[r["tile"]] = r["count"]
    b = tt.tiles.data_boxes()
    far = np.where(counts > 0, g.np_maxdist2(np.array([x]), np.array([y]), b)[0], np.inf)
    order = np.argsort(far, kind="stable")
    reach = np.cumsum(counts[order]) >= k
    r2 = float(far[order][reach.argmax()]) if reach.any() else float("inf")
    near = g.np_mindist2(np.array([x]), np.array([y]), b)[0]
    tiles = [int(t) for t in np.flatnonzero((counts > 0) & (near <= r2))]
    if tt.filters is not None and np.isfinite(r2):
        tiles = [t for t in tiles if obf.may_contain(tt.filters.filters[t], (x, y, r2**0.5 * (1 + 1e-12)))]
    df = df.where(F.col("tile").isin(tiles)).withColumn("dist2", d2)
    if np.isfinite(r2):
        df = df.where(F.col("dist2") <= r2)
    top = df.orderBy("dist2", "pid", "x", "y").limit(max(0, k)).select("pid", "x", "y", "dist2")
    from pyspark.sql import Window

    return top.withColumn("rank", F.row_number().over(Window.orderBy("dist2", "pid", "x", "y")))
