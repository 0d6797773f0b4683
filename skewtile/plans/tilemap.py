"""Tile maps: disjoint half-open boxes that cover the whole plane, kept as a binary tree of cuts."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType

from skewtile.functions import geometry as g

INF = float("inf")
CODEGEN_TILES = 64
"""Maps of up to so many tiles become Column expressions; larger ones go to vectorised Arrow functions."""


@dataclass(frozen=True)
class TileMap:
    """axis[i] is 0 or 1 with a cut, or -1 at a leaf, whose tile is left[i]. Points below the cut go left.

    Outer edges are infinite, so every point has exactly one tile. mbr holds the tight box of each tile's data
    (NaN when unknown: the tile's box clipped to the sample's bounds then serves)."""

    axis: np.ndarray
    cut: np.ndarray
    left: np.ndarray
    right: np.ndarray
    bounds: tuple[float, float, float, float]
    kind: str = "kd"
    mbr: np.ndarray | None = field(default=None, compare=False)

    @property
    def n_tiles(self) -> int:
        return int((self.axis < 0).sum())

    def boxes(self) -> np.ndarray:
        """(n_tiles, 4) regions x1, y1, x2, y2 with infinite outer edges."""
        out = np.empty((self.n_tiles, 4))
        stack = [(0, [-INF, -INF, INF, INF])]
        while stack:
            i, box = stack.pop()
            a = self.axis[i]
            if a < 0:
                out[self.left[i]] = box
            else:
                low, high = box.copy(), box.copy()
                low[2 + a] = high[a] = self.cut[i]
                stack += [(self.left[i], low), (self.right[i], high)]
        return out

    def finite_boxes(self) -> np.ndarray:
        b, (x1, y1, x2, y2) = self.boxes(), self.bounds
        return np.column_stack([np.clip(b[:, 0], x1, x2), np.clip(b[:, 1], y1, y2), np.clip(b[:, 2], x1, x2), np.clip(b[:, 3], y1, y2)])

    def data_boxes(self) -> np.ndarray:
        """Boxes that hold all data of each tile: the tight ones where known. Tiles without data have an empty box."""
        return self.boxes() if self.mbr is None else self.mbr

    # builders -----------------------------------------------------------------------------------

    @classmethod
    def _grow(cls, pts: np.ndarray, n_tiles: int, choose, kind: str, bounds=None) -> TileMap:
        """choose(points, tiles wanted, box, depth) -> (axis, cut, tiles on the left) or None for a leaf."""
        if bounds is None:
            bounds = (*pts.min(0), *pts.max(0)) if len(pts) else (0.0, 0.0, 1.0, 1.0)
        axis, cut, left, right = [], [], [], []
        tiles = 0

        def build(p: np.ndarray, n: int, box, depth: int) -> int:
            nonlocal tiles
            i = len(axis)
            axis.append(-1), cut.append(0.0), left.append(-1), right.append(-1)
            how = choose(p, n, box, depth)
            if how is None:
                left[i], tiles = tiles, tiles + 1
                return i
            a, c, n_left = how
            low, high = list(box), list(box)
            low[2 + a] = high[a] = c
            below = p[:, a] < c
            axis[i], cut[i] = a, c
            left[i] = build(p[below], n_left, low, depth + 1)
            right[i] = build(p[~below], n - n_left, high, depth + 1)
            return i

        build(pts, n_tiles, bounds, 0)
        return cls(np.array(axis), np.array(cut, float), np.array(left), np.array(right), tuple(map(float, bounds)), kind)

    @staticmethod
    def _cut_at(p: np.ndarray, a: int, share: float) -> float | None:
        """A value that leaves about this share of the points below it; None where all are equal."""
        v = np.sort(p[:, a])
        if not len(v) or v[0] == v[-1]:
            return None
        c = v[min(len(v) - 1, max(1, round(share * len(v))))]
        return float(c if c > v[0] else v[v > v[0]][0])

    @classmethod
    def kd(cls, pts: np.ndarray, n_tiles: int) -> TileMap:
        """Equal-count halves, along the longer side."""

        def choose(p, n, box, depth):
            if n < 2 or len(p) < 2:
                return None
            spread = p.max(0) - p.min(0)
            for a in np.argsort(-spread, kind="stable"):
                if (c := cls._cut_at(p, int(a), (n // 2) / n)) is not None:
                    return int(a), c, n // 2
            return None

        return cls._grow(pts, n_tiles, choose, "kd")

    @classmethod
    def str_pack(cls, pts: np.ndarray, n_tiles: int) -> TileMap:
        """R-tree-like packing: about sqrt(n) slabs of equal counts along x, each packed along y."""
        slabs = max(1, round(n_tiles**0.5))
        quota = [n_tiles // slabs + (i < n_tiles % slabs) for i in range(slabs)]

        def plan(n: int) -> int:
            """Tiles left of the cut, at a slab's border while there are several slabs."""
            for s in range(len(quota)):
                for e in range(s + 2, len(quota) + 1):
                    if sum(quota[s:e]) == n:
                        return sum(quota[s : (s + e) // 2])
            return 0

        def choose(p, n, box, depth):
            if n < 2 or len(p) < 2:
                return None
            k = plan(n) if n > max(quota) else 0
            a, k = (0, k) if k else (1, n // 2)
            for axis in (a, 1 - a):
                if (c := cls._cut_at(p, axis, k / n)) is not None:
                    return axis, c, k
            return None

        return cls._grow(pts, n_tiles, choose, "str")

    @classmethod
    def quadtree(cls, pts: np.ndarray, n_tiles: int) -> TileMap:
        """The box with most points is quartered at its middle until there are n_tiles or more."""
        bounds = (*pts.min(0), *pts.max(0)) if len(pts) else (0.0, 0.0, 1.0, 1.0)
        leaves = [(len(pts), tuple(map(float, bounds)), pts, 0)]
        split: set[tuple] = set()
        while len(leaves) < n_tiles:
            leaves.sort(key=lambda t: (-t[0], t[1]))
            n, box, p, d = leaves[0]
            if n < 2 or d >= 24 or (p.max(0) == p.min(0)).all():
                break
            split.add(box)
            mx, my = (box[0] + box[2]) / 2, (box[1] + box[3]) / 2
            leaves.pop(0)
            for x in (0, 1):
                for y in (0, 1):
                    sub = p[((p[:, 0] >= mx) == x) & ((p[:, 1] >= my) == y)]
                    leaves.append((len(sub), ((box[0], mx)[x], (box[1], my)[y], (mx, box[2])[x], (my, box[3])[y]), sub, d + 1))

        def choose(p, n, box, depth):
            box = tuple(box)
            if depth % 2 == 0:
                return (0, (box[0] + box[2]) / 2, 0) if box in split else None
            return 1, (box[1] + box[3]) / 2, 0

        return cls._grow(pts, n_tiles, choose, "quadtree", bounds)

    @classmethod
    def grid(cls, bounds: tuple[float, float, float, float], gx: int, gy: int) -> TileMap:
        """Equal boxes, whatever the data."""
        x1, y1, x2, y2 = map(float, bounds)

        def build(lo: tuple[int, int], hi: tuple[int, int]):
            (a, b), (c, d) = lo, hi
            if c - a > 1:
                m = (a + c) // 2
                return 0, x1 + (x2 - x1) * m / gx, build(lo, (m, d)), build((m, b), hi)
            if d - b > 1:
                m = (b + d) // 2
                return 1, y1 + (y2 - y1) * m / gy, build(lo, (c, m)), build((a, m), hi)
            return None

        return cls._from_nested(build((0, 0), (gx, gy)), (x1, y1, x2, y2), "grid")

    @classmethod
    def _from_nested(cls, tree, bounds, kind: str) -> TileMap:
        axis, cut, left, right = [], [], [], []
        tiles = 0

        def put(t) -> int:
            nonlocal tiles
            i = len(axis)
            axis.append(-1), cut.append(0.0), left.append(-1), right.append(-1)
            if t is None:
                left[i], tiles = tiles, tiles + 1
            else:
                axis[i], cut[i] = t[0], t[1]
                left[i] = put(t[2])
                right[i] = put(t[3])
            return i

        put(tree)
        return cls(np.array(axis), np.array(cut, float), np.array(left), np.array(right), tuple(map(float, bounds)), kind)

    def nested(self, i: int = 0, leaf=lambda tile: None):
        if self.axis[i] < 0:
            return leaf(int(self.left[i]))
        return int(self.axis[i]), float(self.cut[i]), self.nested(self.left[i], leaf), self.nested(self.right[i], leaf)

    def split(self, subtrees: dict[int, tuple]) -> tuple[TileMap, dict[int, list[int]]]:
        """Replaces tiles by nested trees of cuts. Returns the new map, and for each old tile its new ones; tiles are renumbered."""
        new = self._from_nested(self.nested(leaf=lambda t: subtrees.get(t)), self.bounds, self.kind)
        count = {t: _leaves(subtrees.get(t)) for t in range(self.n_tiles)}
        at, names = 0, {}
        for t in self._leaf_order():
            names[t] = list(range(at, at + count[t]))
            at += count[t]
        return new, names

    def _leaf_order(self) -> Iterator[int]:
        stack = [0]
        while stack:
            i = stack.pop()
            if self.axis[i] < 0:
                yield int(self.left[i])
            else:
                stack += [self.right[i], self.left[i]]

    def with_mbr(self, mbr: np.ndarray) -> TileMap:
        return TileMap(self.axis, self.cut, self.left, self.right, self.bounds, self.kind, mbr)

    # use ----------------------------------------------------------------------------------------

    def locate(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Tiles of points, by walking all of them down the tree together."""
        node = np.zeros(len(x), np.int64)
        while True:
            a = self.axis[node]
            inner = a >= 0
            if not inner.any():
                return self.left[node]
            value = np.where(a == 0, x, y)
            node = np.where(inner, np.where(value < self.cut[node], self.left[node], self.right[node]), node)

    def tile_of(self, x: Column, y: Column) -> Column:
        """The tile of a point."""
        if self.n_tiles <= CODEGEN_TILES:

            def walk(i: int) -> Column:
                if self.axis[i] < 0:
                    return F.lit(int(self.left[i]))
                return F.when((x, y)[self.axis[i]] < float(self.cut[i]), walk(self.left[i])).otherwise(walk(self.right[i]))

            return walk(0)
        locate = self.locate

        @F.pandas_udf(IntegerType())
        def tile(x: pd.Series, y: pd.Series) -> pd.Series:
            return pd.Series(locate(x.to_numpy(), y.to_numpy()).astype("int32"))

        return tile(x, y)

    def tiles_meeting(self, x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
        """Array of the tiles whose data box meets the closed rectangle."""
        boxes = self.data_boxes()
        if self.n_tiles <= CODEGEN_TILES:
            hit = lambda b: g.rects_meet(x1, y1, x2, y2, *(float(v) for v in b))
            some = [F.when(hit(b), F.lit(t)) for t, b in enumerate(boxes) if not np.isnan(b[0])]
            return F.array_compact(F.array(*some)) if some else F.array().cast("array<int>")
        meet = self.rect_tiles

        @F.pandas_udf(ArrayType(IntegerType()))
        def tiles(x1: pd.Series, y1: pd.Series, x2: pd.Series, y2: pd.Series) -> pd.Series:
            return pd.Series(meet(np.column_stack([x1, y1, x2, y2])))

        return tiles(x1, y1, x2, y2)

    def tiles_in_reach(self, x: Column, y: Column, dx: float, dy: float) -> Column:
        """Array of the tiles whose region, not whose data, a point has within dx and dy."""
        if self.n_tiles <= CODEGEN_TILES:
            hit = lambda b: g.rects_meet(x - dx, y - dy, x + dx, y + dy, *(float(v) for v in b))
            return F.array_compact(F.array(*(F.when(hit(b), F.lit(t)) for t, b in enumerate(self.boxes()))))
        return self.with_mbr(None).tiles_meeting(x - dx, y - dy, x + dx, y + dy)  # a map without data boxes goes by its cuts

    def rect_tiles(self, rects: np.ndarray) -> list[np.ndarray]:
        """For each closed rectangle, the tiles whose data box it meets: a frontier of (query, node) goes down the tree."""
        q, node = np.arange(len(rects)), np.zeros(len(rects), np.int64)
        out_q, out_t = [], []
        while len(q):
            leaf = self.axis[node] < 0
            out_q.append(q[leaf]), out_t.append(self.left[node[leaf]])
            q, node = q[~leaf], node[~leaf]
            a, c = self.axis[node], self.cut[node]
            lo, hi = rects[q, a] < c, rects[q, a + 2] >= c
            q, node = np.concatenate([q[lo], q[hi]]), np.concatenate([self.left[node[lo]], self.right[node[hi]]])
        q, t = np.concatenate(out_q), np.concatenate(out_t)
        if self.mbr is not None and len(q):
            b, r = self.mbr[t], rects[q]
            keep = g.rects_meet(r[:, 0], r[:, 1], r[:, 2], r[:, 3], b[:, 0], b[:, 1], b[:, 2], b[:, 3])
            q, t = q[keep], t[keep]
        order = np.lexsort((t, q))
        return np.split(t[order].astype("int32"), np.searchsorted(q[order], np.arange(1, len(rects)))) if len(rects) else []

    def to_json(self) -> str:
        return json.dumps({"axis": self.axis.tolist(), "cut": self.cut.tolist(), "left": self.left.tolist(), "right": self.right.tolist(), "bounds": self.bounds, "kind": self.kind, "mbr": None if self.mbr is None else self.mbr.tolist()})

    @classmethod
    def from_json(cls, text: str) -> TileMap:
        d = json.loads(text)
        return cls(np.array(d["axis"]), np.array(d["cut"], float), np.array(d["left"]), np.array(d["right"]), tuple(d["bounds"]), d["kind"], None if d["mbr"] is None else np.array(d["mbr"], float))


def by_tile(values: list, tile: Column, kind: str) -> Column:
    """A per-tile constant as a Column: one literal array however large the map, as Spark folds the split of a constant."""
    return F.get(F.split(F.lit(",".join(map(repr, values))), ",").cast(f"array<{kind}>"), tile)


def _leaves(tree) -> int:
    return 1 if tree is None else _leaves(tree[2]) + _leaves(tree[3])


BUILDERS = {"kd": TileMap.kd, "str": TileMap.str_pack, "quadtree": TileMap.quadtree}


def reservoir(df: DataFrame, size: int, seed: int = 11) -> DataFrame:
    """A uniform sample of `size` rows in one pass: the smallest hashes of the ids; ties of ids fall together."""
    return df.orderBy(F.xxhash64("pid", F.lit(seed)), "pid", "x", "y").limit(size)


def bernoulli(df: DataFrame, rate: float, seed: int = 11) -> DataFrame:
    return df.where(F.pmod(F.xxhash64("pid", F.lit(seed)), F.lit(1 << 20)) < int(rate * (1 << 20)))


def by_key_mod(df: DataFrame, m: int, r: int = 0, key: str = "pid") -> DataFrame:
    return df.where(F.col(key) % m == r)


def sample_points(df: DataFrame, size: int, seed: int = 11) -> np.ndarray:
    """The sample at the driver; `size` bounds it."""
    rows = reservoir(df.select("pid", "x", "y"), size, seed).select("x", "y").toPandas()
    return rows.to_numpy(float).reshape(-1, 2)


def build_map(df: DataFrame, n_tiles: int, kind: str = "kd", sample: int = 4096, grid_side: int | None = None) -> TileMap:
    """A tile map of one kind over a sample of df; grids take the bounds of all points."""
    if kind == "grid":
        side = grid_side or max(1, round(n_tiles**0.5))
        r = df.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y")).first()
        return TileMap.grid(tuple(v if v is not None else float(i > 1) for i, v in enumerate(r)), side, side)
    return BUILDERS[kind](sample_points(df, sample), n_tiles)
