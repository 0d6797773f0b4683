"""Searches and joins of shapes other than points: rows (sid, kind, pts, x1, y1, x2, y2) with vertices and their box."""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from skewtile.functions import geometry as g
from skewtile.functions.geometry import rects_meet
from skewtile.operators import blocks
from skewtile.operators import local as kernels
from skewtile.plans.tilemap import TileMap

PTS = "array<struct<x:double,y:double>>"


def with_box(shapes: DataFrame) -> DataFrame:
    """Adds x1, y1, x2, y2 from pts."""
    side = lambda f, c: f(F.transform("pts", lambda p: p[c]))
    return shapes.withColumns({"x1": side(F.array_min, "x"), "y1": side(F.array_min, "y"), "x2": side(F.array_max, "x"), "y2": side(F.array_max, "y")})


def rect_shape(sid: Column, x1: Column, y1: Column, x2: Column, y2: Column) -> list[Column]:
    corner = lambda x, y: F.struct(x.cast("double").alias("x"), y.cast("double").alias("y"))
    return [sid.alias("sid"), F.lit("rect").alias("kind"), F.array(corner(x1, y1), corner(x2, y1), corner(x2, y2), corner(x1, y2)).alias("pts"), x1.alias("x1"), y1.alias("y1"), x2.alias("x2"), y2.alias("y2")]


def paths(events: DataFrame) -> DataFrame:
    """One polyline per user through its points in time order; events: pid, x, y, user_id, ts."""
    rows = events.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("ts", "pid", "x", "y"))).alias("_p"))
    return with_box(rows.select(F.col("user_id").alias("sid"), F.lit("polyline").alias("kind"), F.transform("_p", lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y"))).alias("pts")))


def _pairs(kind_a, a, kind_b, b, predicate: str, r: float) -> np.ndarray:
    test = {"intersects": g.shapes_intersect, "contains": g.shape_contains, "within": lambda ka, p, kb, q: g.shape_contains(kb, q, ka, p), "within_distance": lambda ka, p, kb, q: g.shapes_within(ka, p, kb, q, r)}[predicate]
    point = lambda s: [(p["x"], p["y"]) for p in s]
    return np.array([test(ka, point(p), kb, point(q)) for ka, p, kb, q in zip(kind_a, a, kind_b, b)], bool)


def refine(pairs: DataFrame, predicate: str = "intersects", r: float = 0.0) -> DataFrame:
    """Keeps the pairs (akind, apts, bkind, bpts, ...) that pass the exact test, batch by batch."""

    @F.pandas_udf("boolean")
    def exact(ka: pd.Series, a: pd.Series, kb: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(_pairs(ka, a, kb, b, predicate, r))

    return pairs.where(exact("akind", "apts", "bkind", "bpts"))


def shape_search(shapes: DataFrame, x1: float, y1: float, x2: float, y2: float) -> DataFrame:
    """Shapes that meet a closed window: boxes by Columns, then the exact test; shapes whose box lies inside pass at once."""
    near = shapes.where(rects_meet(F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"), F.lit(x1), F.lit(y1), F.lit(x2), F.lit(y2)))
    window = F.array(*(F.struct(F.lit(a).alias("x"), F.lit(b).alias("y")) for a, b in ((x1, y1), (x2, y1), (x2, y2), (x1, y2))))
    inside = (F.col("x1") >= x1) & (F.col("x2") <= x2) & (F.col("y1") >= y1) & (F.col("y2") <= y2) | (F.col("kind") == "rect")
    doubt = near.where(~inside).withColumns({"akind": F.col("kind"), "apts": F.col("pts"), "bkind": F.lit("rect"), "bpts": window})
    return near.where(inside).unionByName(refine(doubt).drop("akind", "apts", "bkind", "bpts"))


def shape_join(a: DataFrame, b: DataFrame, predicate: str = "intersects", r: float = 0.0, cell: float | None = None, exact: bool = True) -> DataFrame:
    """(asid, bsid) of shapes that pass the predicate. Boxes meet in cells of the plane; a pair is kept only in the cell of the lower left
    corner of its boxes' common part, so it comes once without a distinct."""
    if cell is None:
        got = a.agg(F.percentile_approx(F.greatest(F.col("x2") - F.col("x1"), F.col("y2") - F.col("y1")), 0.5, 1000)).first()[0]
        cell = max(float(got or 1.0), 1.0)
    named = lambda df, n: df.select(*(F.col(c).alias(n + c) for c in ("sid", *(("kind", "pts") if exact else ()), "x1", "y1", "x2", "y2")))
    a, b = named(a, "a"), named(b, "b")
    a = a.withColumns({"ax1": F.col("ax1") - r, "ay1": F.col("ay1") - r, "ax2": F.col("ax2") + r, "ay2": F.col("ay2") + r})
    at = lambda c: F.floor(c / cell)

    def keyed(df: DataFrame, n: str) -> DataFrame:
        df = df.withColumn("cx", F.explode(F.sequence(at(F.col(n + "x1")), at(F.col(n + "x2")))))
        return df.withColumn("cy", F.explode(F.sequence(at(F.col(n + "y1")), at(F.col(n + "y2")))))

    near = keyed(a, "a").join(keyed(b, "b"), ["cx", "cy"])
    near = near.where(rects_meet(*(F.col(c) for c in ("ax1", "ay1", "ax2", "ay2", "bx1", "by1", "bx2", "by2"))))
    near = near.where((F.col("cx") == at(F.greatest("ax1", "bx1"))) & (F.col("cy") == at(F.greatest("ay1", "by1"))))
    return (refine(near, predicate, r) if exact else near).select("asid", "bsid")


def assign_shapes(shapes: DataFrame, tm: TileMap) -> tuple[DataFrame, TileMap, np.ndarray]:
    """Shapes with the tile of their box's middle, so each has one, the map with every tile's tight box around its shapes, and their counts: a
    row a tile comes to the driver."""
    placed = shapes.withColumn("tile", tm.tile_of((F.col("x1") + F.col("x2")) / 2, (F.col("y1") + F.col("y2")) / 2))
    mbr, counts = np.full((tm.n_tiles, 4), np.nan), np.zeros(tm.n_tiles, np.int64)
    for t, *b, n in placed.groupBy("tile").agg(F.min("x1"), F.min("y1"), F.max("x2"), F.max("y2"), F.count(F.lit(1))).collect():
        mbr[t], counts[t] = b, n
    return placed, tm.with_mbr(mbr), counts


def tile_shape_join(a: DataFrame, b: DataFrame, tm: TileMap, predicate: str = "intersects", r: float = 0.0, exact: bool = True, local: str = "catalyst") -> DataFrame:
    """(asid, bsid) of shapes that pass the predicate: b lies by tiles, and each shape of a is sent to the tiles whose shapes' box it meets.

    local: "catalyst" (pairs of a tile by their boxes), or "auto", which takes the local planner's choice for shapes: two trees a tile."""
    held, tm, counts = assign_shapes(b, tm)
    grown = [F.col("x1") - r, F.col("y1") - r, F.col("x2") + r, F.col("y2") + r]
    sent = a.select("sid", "kind", "pts", *(g.alias(c) for g, c in zip(grown, ("x1", "y1", "x2", "y2"))))
    sent = sent.withColumn("tile", F.explode(tm.tiles_meeting(*(F.col(c) for c in ("x1", "y1", "x2", "y2")))))
    if local == "auto" and kernels.choose("shape", 1, 1) == "dual_tree":
        return _tree_pairs(sent, held, counts, predicate, r, exact)
    named = lambda df, n: df.select("tile", *(F.col(c).alias(n + c) for c in ("sid", *(("kind", "pts") if exact else ()), "x1", "y1", "x2", "y2")))
    near = named(sent, "a").join(named(held, "b"), "tile").where(rects_meet(*(F.col(c) for c in ("ax1", "ay1", "ax2", "ay2", "bx1", "by1", "bx2", "by2"))))
    return (refine(near, predicate, r) if exact else near).select("asid", "bsid")


def _tree_pairs(sent: DataFrame, held: DataFrame, counts: np.ndarray, predicate: str, r: float, exact: bool) -> DataFrame:
    """Two trees over a part of a tile's shapes and a batch of those sent there; pairs leave in pieces of bounded size."""
    box, more = ("x1", "y1", "x2", "y2"), ("kind", "pts") if exact else ()
    plain = lambda b, *names: [b.column(c).to_numpy(zero_copy_only=False) for c in names]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sid, *rest, windows = blocks.first_side(batches, ("id", *box, *more))
        ask = kernels.boxes_probe(np.column_stack(rest[:4])) if len(sid) else None
        for w in windows if len(sid) else ():
            asid, a = w.column("id").to_numpy(), plain(w, *more)
            for i, j in ask(np.column_stack(plain(w, *box))):
                if exact and len(i):
                    yes = _pairs(a[0][i], a[1][i], rest[4][j], rest[5][j], predicate, r)
                    i, j = i[yes], j[yes]
                if len(i):
                    yield pa.RecordBatch.from_arrays([pa.array(asid[i]), pa.array(sid[j])], ["asid", "bsid"])

    columns = ["tile", F.col("sid").cast("long").alias("id"), *(F.col(c).cast("double").alias(c) for c in box), *more]
    return blocks.dealt(held.select(*columns), sent.select(*columns), counts, []).applyInArrow(run, "asid long, bsid long")


# polylines and rings in Columns -----------------------------------------------------------------


def polyline_length(pts: Column) -> Column:
    ends = F.zip_with(F.slice(pts, F.lit(1), F.greatest(F.size(pts) - 1, F.lit(0))), F.slice(pts, F.lit(2), F.greatest(F.size(pts) - 1, F.lit(0))), lambda a, b: F.hypot(b["x"] - a["x"], b["y"] - a["y"]))
    return F.aggregate(ends, F.lit(0.0), lambda s, v: s + v)


def ring_area(pts: Column) -> Column:
    """Twice-signed cross products, halved and made positive."""
    turned = F.concat(F.slice(pts, F.lit(2), F.greatest(F.size(pts) - 1, F.lit(0))), F.slice(pts, F.lit(1), F.lit(1)))
    cross = F.zip_with(pts, turned, lambda a, b: a["x"] * b["y"] - b["x"] * a["y"])
    return F.abs(F.aggregate(cross, F.lit(0.0), lambda s, v: s + v)) / 2


# well-known binary ------------------------------------------------------------------------------


def point_wkb(x: Column, y: Column) -> Column:
    @F.pandas_udf("binary")
    def pack(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([struct.pack("<BIdd", 1, 1, a, b) for a, b in zip(x, y)])

    return pack(x, y)


def wkb_point(wkb: Column) -> Column:
    def read(b: bytes) -> tuple[float, float]:
        order = "<" if b[0] == 1 else ">"
        kind, x, y = struct.unpack(order + "Idd", b[1:21])
        if kind != 1:
            raise ValueError("not a point")
        return x, y

    @F.pandas_udf("struct<x:double,y:double>")
    def unpack(wkb: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([read(bytes(b)) for b in wkb], columns=["x", "y"])

    return unpack(wkb)


def segments(events: DataFrame) -> DataFrame:
    """Each user's moves: (user_id, pid, x, y, to_x, to_y) in time order."""
    order = Window.partitionBy("user_id").orderBy("ts", "pid")
    return events.withColumns({"to_x": F.lead("x").over(order), "to_y": F.lead("y").over(order)}).where("to_x IS NOT NULL")
