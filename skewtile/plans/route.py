"""Routing: which tiles a query must visit."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skewtile.functions.geometry import mindist2, np_maxdist2
from skewtile.plans.filterstore import FilterStore
from skewtile.plans.tilemap import TileMap, by_tile


def ranges(q: DataFrame, tm: TileMap, filters: FilterStore | None = None) -> DataFrame:
    """One row per window and tile whose data it may meet; with filters, tiles that surely hold nothing there are left out."""
    routed = q.withColumn("tile", F.explode(tm.tiles_meeting(F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"))))
    return filters.prune(routed) if filters is not None else routed


def home(q: DataFrame, tm: TileMap) -> DataFrame:
    """Focal points (qid, cx, cy) with the tile they lie in."""
    return q.withColumn("tile", tm.tile_of(F.col("cx"), F.col("cy")))


def circles(q: DataFrame, tm: TileMap, r2: Column, filters: FilterStore | None = None) -> DataFrame:
    """One row per focal point and tile that its disc (cx, cy, squared radius r2) meets."""
    r = F.sqrt(r2) * (1 + 1e-12)
    q = q.withColumn("r2", r2)
    met = tm.tiles_meeting(F.col("cx") - r, F.col("cy") - r, F.col("cx") + r, F.col("cy") + r)
    routed = q.withColumn("tile", F.explode(met)).where(meets_disc(tm))
    return prune_discs(routed, filters)


def meets_disc(tm: TileMap) -> Column:
    """Whether the data box of `tile` is within the squared radius r2 of (cx, cy), however many tiles there are."""
    boxes = tm.data_boxes()
    edge = [by_tile(boxes[:, k].tolist(), F.col("tile"), "double") for k in range(4)]
    return mindist2(F.col("cx"), F.col("cy"), *edge) <= F.col("r2")


def prune_discs(routed: DataFrame, filters: FilterStore | None, keep: Column | None = None) -> DataFrame:
    """Without the rows whose disc surely holds nothing in their tile; rows of which `keep` is true stay."""
    if filters is None:
        return routed
    return filters.prune(routed.withColumn("_r", F.sqrt("r2") * (1 + 1e-12)), ("cx", "cy", "_r"), keep).drop("_r")


def bound_from_counts(cx: Column, cy: Column, tm: TileMap, counts: np.ndarray, k: Column, known: Column | None = None) -> Column:
    """A squared radius within which each focal point surely has k points: tiles by their farthest corner, until their counts
    reach k. Infinite where all tiles together have fewer. known: radii that are taken as they are where not null, at no cost."""
    boxes, counts = tm.mbr, np.asarray(counts)
    use = counts > 0
    boxes, counts = boxes[use], counts[use]
    if not len(boxes):
        return F.lit(float("inf")) if known is None else F.coalesce(known, F.lit(float("inf")))

    @F.pandas_udf("double")
    def bound(cx: pd.Series, cy: pd.Series, k: pd.Series, known: pd.Series) -> pd.Series:
        out = known.to_numpy(float, na_value=np.nan).copy()
        todo = np.flatnonzero(np.isnan(out))
        out[todo] = np.inf
        step = max(1, (1 << 22) // max(1, len(boxes)))
        for a in range(0, len(todo), step):
            at = todo[a : a + step]
            d = np_maxdist2(cx.to_numpy()[at], cy.to_numpy()[at], boxes)
            order = np.argsort(d, axis=1, kind="stable")
            enough = np.cumsum(counts[order], axis=1) >= k.to_numpy()[at, None]
            first = enough.argmax(1)
            rows = np.arange(len(d))
            out[at] = np.where(enough.any(1), d[rows, order[rows, first]], np.inf)
        return pd.Series(out)

    return bound(cx, cy, k, F.lit(None).cast("double") if known is None else known)
