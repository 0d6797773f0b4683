"""Filters of all tiles: built on the workers, held at the driver as packed bits, refreshed by what queries found empty."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skewtile.plans import obf
from skewtile.plans.tilemap import TileMap

ROW = "tile int, version int, data_version int, x1 double, y1 double, x2 double, y2 double, n_internal int, internal binary, leaf binary, n_bits int"
DRIVER_BITS = 128 << 23
"""Bits of all filters together that the driver holds and sends to the tasks; beyond, each tile's filter is shrunk to its share."""


def to_row(tile: int, f: obf.Filter) -> dict:
    internal, leaf = f.pack()
    return {"tile": tile, "version": f.version, "data_version": f.data_version, **dict(zip(("x1", "y1", "x2", "y2"), f.box)), "n_internal": f.n_internal, "internal": internal, "leaf": leaf, "n_bits": f.size_bits}


def from_row(r) -> obf.Filter:
    return obf.Filter.unpack((r["x1"], r["y1"], r["x2"], r["y2"]), bytes(r["internal"]), bytes(r["leaf"]), r["n_internal"], r["version"], r["data_version"])


def build_rows(tiled: DataFrame, tm: TileMap, max_depth: int = 7, leaf_cap: int = 1, max_bits: int | None = None) -> DataFrame:
    """One filter row per tile with data, over the tight box of its data (tm must have those). What a worker needs of a tile are its
    occupied cells of the finest level and how many points each has, so those are counted first and a
    task gets at most 4 ** max_depth rows of a tile, however many points it has."""
    boxes = [tuple(map(float, b)) for b in tm.mbr]
    side = float(1 << max_depth)
    box = F.array(*(F.array(*(F.lit(v) for v in b)) for b in boxes)) if len(boxes) <= 64 else None
    if box is None:
        table = tiled.sparkSession.createDataFrame([(t, *b) for t, b in enumerate(boxes)], "tile int, bx1 double, by1 double, bx2 double, by2 double")
        located = tiled.join(F.broadcast(table) if len(boxes) <= 1 << 16 else table, "tile")
        edge = [F.col(c) for c in ("bx1", "by1", "bx2", "by2")]
    else:
        located = tiled.withColumn("_box", F.get(box, F.col("tile")))
        edge = [F.get("_box", i) for i in range(4)]
    cell = lambda v, lo, hi: F.least(F.greatest(F.floor((v - lo) / F.greatest(hi - lo, F.lit(1e-300)) * side), F.lit(0)), F.lit(int(side) - 1)).cast("int")
    cells = located.select("tile", cell(F.col("x"), edge[0], edge[2]).alias("gx"), cell(F.col("y"), edge[1], edge[3]).alias("gy"))
    cells = cells.groupBy("tile", "gx", "gy").agg(F.count(F.lit(1)).alias("n"))

    def make(pdf: pd.DataFrame) -> pd.DataFrame:
        tile = int(pdf["tile"].iloc[0])
        f = from_cells(pdf["gx"].to_numpy(), pdf["gy"].to_numpy(), pdf["n"].to_numpy(), boxes[tile], max_depth, leaf_cap)
        return pd.DataFrame([to_row(tile, obf.shrink(f, max_bits) if max_bits else f)])

    return cells.groupBy("tile").applyInPandas(make, ROW)


def from_cells(gx: np.ndarray, gy: np.ndarray, n: np.ndarray, box: obf.Box, max_depth: int, leaf_cap: int = 1) -> obf.Filter:
    """The filter of obf.build from counts of the finest cells."""

    def cell(gx, gy, n, side: int, depth: int):
        if not len(n):
            return False
        if depth == max_depth or n.sum() <= leaf_cap and depth > 0:
            return True
        half = side // 2
        out = []
        for e, north in obf.QUADRANTS:
            use = ((gx >= half) == bool(e)) & ((gy >= half) == bool(north))
            out.append(cell(gx[use] - half * e, gy[use] - half * north, n[use], half, depth + 1))
        return out

    return obf.encode(cell(gx, gy, n, 1 << max_depth, 0), box)


class _Unpacked:
    """A worker's view of the broadcast filters: those that its rows ask for are unpacked, once."""

    def __init__(self, sent):
        self.sent, self.known = sent, {}

    def get(self, tile: int) -> obf.Filter | None:
        if tile not in self.known:
            packed = self.sent.value.get(tile)
            self.known[tile] = None if packed is None else obf.Filter.unpack(*packed)
        return self.known[tile]


@dataclass(frozen=True)
class FilterStore:
    """The driver's copy: immutable, a refresh makes a new one."""

    filters: dict[int, obf.Filter]
    version: int = 0

    @classmethod
    def collect(cls, rows: DataFrame, n_tiles: int) -> FilterStore:
        """Bounded: each filter is shrunk on its worker to its share of DRIVER_BITS before it comes here."""
        share = max(64, DRIVER_BITS // max(1, n_tiles))

        def fit(it: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in it:
                yield pd.DataFrame([to_row(r["tile"], obf.shrink(from_row(r), share) if r["n_bits"] > share else from_row(r)) for r in pdf.to_dict("records")], columns=list(pdf.columns))

        return cls({r["tile"]: from_row(r) for r in rows.mapInPandas(fit, ROW).collect()})

    @property
    def size_bits(self) -> int:
        return sum(f.size_bits for f in self.filters.values())

    @cached_property
    def _packed(self) -> dict[int, tuple]:
        """What is sent: a tile's filter as packed bytes."""
        return {t: (f.box, *f.pack(), f.n_internal, f.version, f.data_version) for t, f in self.filters.items()}

    def prune(self, routed: DataFrame, columns: tuple[str, ...] = ("x1", "y1", "x2", "y2"), keep: Column | None = None) -> DataFrame:
        """Drops routed rows whose tile surely has nothing in their range, but for those of which `keep` is true. columns: of a rectangle, or
        (x, y, r)."""
        sent = routed.sparkSession.sparkContext.broadcast(self._packed)  # DRIVER_BITS at most
        filters = _Unpacked(sent)

        @F.pandas_udf("boolean")
        def may(tile: pd.Series, *shape: pd.Series) -> pd.Series:
            rows = np.column_stack([s.to_numpy(float) for s in shape])
            whole = ~np.isfinite(rows).all(1)  # no end to look up: such a shape passes wherever there are data
            rows[whole] = 0.0
            slack = 1e-9 * (1 + np.abs(rows).max(1))  # cell borders are rounded
            rows = rows + slack[:, None] * np.array([-1, -1, 1, 1] if len(shape) == 4 else [0, 0, 1])
            out = np.zeros(len(tile), bool)
            for t, at in tile.groupby(tile).indices.items():
                f = filters.get(t)
                out[at] = False if f is None else obf.may_contain_batch(f, rows[at]) | whole[at]
            return pd.Series(out)

        held = may(F.col("tile"), *(F.col(c) for c in columns))
        return routed.where(held if keep is None else keep | held)

    def refresh(self, tiled: DataFrame, empty_probes: DataFrame, border: str = "exact", max_depth: int = 9, max_bits: int | None = None, policy: str = "deepest") -> FilterStore:
        """policy: what goes first where a filter outgrows max_bits; "lru" and "mru" go by how many of the probes visit a node.

        empty_probes: (tile, x1, y1, x2, y2) that were searched and had no answer in that tile. The workers that hold the tiles learn from
        them; tiles without such probes keep their filter."""
        filters = self.filters
        probes = empty_probes.select("tile", "x1", "y1", "x2", "y2").distinct()
        # the exact border rule needs only the points in cells that a probe crosses, and no cell before the first cut is wider than the box
        edge = probes.select(F.col("tile").alias("_t"), "x1", "y1", "x2", "y2").groupBy("_t").agg(F.min("x1").alias("a"), F.min("y1").alias("b"), F.max("x2").alias("c"), F.max("y2").alias("d"))
        near = tiled.join(edge, F.col("tile") == F.col("_t")) if border == "exact" else tiled.limit(0)
        if border == "exact":
            wide = max((f.box[2] - f.box[0] for f in filters.values()), default=0.0) / 2, max((f.box[3] - f.box[1] for f in filters.values()), default=0.0) / 2
            near = near.where((F.col("x") >= F.col("a") - wide[0]) & (F.col("x") <= F.col("c") + wide[0]) & (F.col("y") >= F.col("b") - wide[1]) & (F.col("y") <= F.col("d") + wide[1]))
        near = near.select("tile", "x", "y").distinct()  # occupancy asks for places, not for how many points are there

        def learn(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
            tile = int(key[0])
            if tile not in filters or not len(b):
                return pd.DataFrame(columns=[c.split()[0] for c in ROW.split(", ")])
            f = filters[tile]
            points = (a["x"].to_numpy(), a["y"].to_numpy()) if border == "exact" else None
            shapes = b[["x1", "y1", "x2", "y2"]].to_numpy()
            f = obf.mark_all_empty(f, shapes, border, max_depth, points)
            if max_bits:
                f = obf.shrink(f, max_bits, policy, obf.visits(f, shapes) if policy != "deepest" else None)
            f = replace(f, version=filters[tile].version + 1)
            return pd.DataFrame([to_row(tile, f)])

        rows = near.groupBy("tile").cogroup(probes.groupBy("tile")).applyInPandas(learn, ROW)
        new = {r["tile"]: from_row(r) for r in rows.collect()}  # a bounded row a tile
        return FilterStore({**filters, **{t: obf.merge(filters[t], f) for t, f in new.items()}}, self.version + 1)
