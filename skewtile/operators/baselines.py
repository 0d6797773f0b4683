"""The systems that the engine is compared with, each with the physical shape that sets it apart."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from skewtile.functions.geometry import dist2, in_circle, in_rect
from skewtile.operators import blocks, knnjoin, merge
from skewtile.operators import local as kernels
from skewtile.operators.rangejoin import planned, range_join
from skewtile.operators.tiled import TiledTable
from skewtile.plans import obf, route

BROADCAST_QUERIES = 1_000_000
"""Queries that the baselines which send all of them everywhere accept."""
BROADCAST_TILES = 1 << 16
QUERIES_AT_ONCE = 1 << 13


def _bounded(q: DataFrame) -> DataFrame:
    n = q.count()
    if n > BROADCAST_QUERIES:
        raise ValueError(f"this baseline broadcasts its queries; {n} are too many")
    return q


def allparts_range(q: DataFrame, tt: TiledTable, local: str = "inl_rtree") -> DataFrame:
    """Tiles and local indexes, but every tile is asked every query. A tile's rows are indexed in parts of bounded size, the queries pass each
    part in batches, and the pairs leave in pieces."""
    rects = _bounded(q).select("qid", "x1", "y1", "x2", "y2").toPandas()
    ids, boxes = rects["qid"].to_numpy(np.int64), rects[["x1", "y1", "x2", "y2"]].to_numpy(float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pid, x, y, _ = blocks.first_side(batches, ("pid", "x", "y"))
        ask = kernels.PROBES[local](x, y)
        for a in range(0, len(boxes), QUERIES_AT_ONCE):
            for qi, di in ask(boxes[a : a + QUERIES_AT_ONCE]):
                if len(qi):
                    yield pa.RecordBatch.from_arrays([pa.array(ids[a + qi]), pa.array(pid[di])], ["qid", "pid"])

    rows = tt.rows.select("tile", F.col("pid").cast("long"), F.col("x").cast("double"), F.col("y").cast("double"), F.lit(False).alias("second"))
    return blocks.parts(rows, tt.counts, "pid").applyInArrow(run, "qid long, pid long")


def allparts_knn(q: DataFrame, tt: TiledTable, k: int, local: str = "inl_rtree") -> DataFrame:
    """Every tile gives its k best for every focal point; all of them are sorted at the end."""
    points = _bounded(q).select("qid", "cx", "cy").toPandas()
    ids, cx, cy = (points[c].to_numpy() for c in ("qid", "cx", "cy"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pid, x, y = (pdf[c].to_numpy() for c in ("pid", "x", "y"))
        qi, di, d = kernels.knn(local, pid, x, y, cx, cy, k)
        return pd.DataFrame({"qid": ids[qi], "pid": pid[di], "x": x[di], "y": y[di], "dist2": d})

    found = tt.rows.select("tile", F.col("pid").cast("long"), "x", "y").groupBy("tile").applyInPandas(run, "qid long, pid long, x double, y double, dist2 double")
    return merge.topk(found, k)


def tilescan_range(q: DataFrame, tt: TiledTable, mode: str = "no_index", path: str | None = None) -> DataFrame:
    """Tiles are joined and scanned whole. "no_index": every tile, for every window. "disk_index": those that a list of tiles, written to disk
    and read for each batch, says the window overlaps."""
    q = q.select("qid", "x1", "y1", "x2", "y2")
    if mode == "disk_index":
        spark = tt.df.sparkSession
        tt.stats().select("tile", "mx1", "my1", "mx2", "my2").write.mode("overwrite").parquet(path)
        index = spark.read.parquet(path)
        meets = (F.col("x1") <= F.col("mx2")) & (F.col("mx1") <= F.col("x2")) & (F.col("y1") <= F.col("my2")) & (F.col("my1") <= F.col("y2"))
        routed = q.join(F.broadcast(index) if tt.tiles.n_tiles <= BROADCAST_TILES else index, meets).select("qid", "x1", "y1", "x2", "y2", "tile")
    else:
        return allparts_range(q, tt, "sweep")
    hits = tt.rows.select("pid", "x", "y", "tile").join(routed, "tile")
    return hits.where(in_rect(F.col("x"), F.col("y"), F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"))).select("qid", "pid")


def _chunks(batches: Iterator[pa.RecordBatch], size: int = 1 << 18) -> Iterator[list[np.ndarray]]:
    """The columns of many batches as arrays of about `size` rows."""
    held, n = [], 0
    for b in batches:
        held.append(b)
        if (n := n + b.num_rows) >= size:
            yield [c.to_numpy() for c in pa.Table.from_batches(held).columns]
            held, n = [], 0
    if n:
        yield [c.to_numpy() for c in pa.Table.from_batches(held).columns]


def _placed(points: DataFrame) -> DataFrame:
    return points.select(F.col("pid").cast("long"), F.col("x").cast("double"), F.col("y").cast("double")).where("NOT isnan(x) AND NOT isnan(y) AND x IS NOT NULL AND y IS NOT NULL")


def cartesian_range(q: DataFrame, points: DataFrame) -> DataFrame:
    """No tiles and no spatial index: all queries go to every partition of the points, which are swept in the order of x."""
    rects = _bounded(q).select("qid", "x1", "y1", "x2", "y2").toPandas()
    ids, boxes = rects["qid"].to_numpy(np.int64), rects[["x1", "y1", "x2", "y2"]].to_numpy(float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for pid, x, y in _chunks(batches):
            ask = kernels.sweep_probe(x, y)
            for a in range(0, len(boxes), QUERIES_AT_ONCE):
                for qi, di in ask(boxes[a : a + QUERIES_AT_ONCE]):
                    if len(qi):
                        yield pa.RecordBatch.from_arrays([pa.array(ids[a + qi]), pa.array(pid[di])], ["qid", "pid"])

    return _placed(points).repartition(4 * points.sparkSession.sparkContext.defaultParallelism).mapInArrow(run, "qid long, pid long")


def cartesian_knn(q: DataFrame, points: DataFrame, k: int) -> DataFrame:
    """No tiles and no spatial index: every partition of the points gives its k best for every focal point."""
    focal = _bounded(q).select("qid", "cx", "cy").toPandas()
    ids, cx, cy = (focal[c].to_numpy() for c in ("qid", "cx", "cy"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for pid, x, y in _chunks(batches):
            for a in range(0, len(ids), QUERIES_AT_ONCE):
                qi, di, d = kernels.knn("sweep", pid, x, y, cx[a : a + QUERIES_AT_ONCE], cy[a : a + QUERIES_AT_ONCE], k)
                yield pa.RecordBatch.from_arrays([pa.array(v) for v in (ids[a + qi], pid[di], x[di], y[di], d)], ["qid", "pid", "x", "y", "dist2"])

    rows = _placed(points).repartition(4 * points.sparkSession.sparkContext.defaultParallelism)
    return merge.topk(rows.mapInArrow(run, "qid long, pid long, x double, y double, dist2 double"), k)


def pivot_knn(q: DataFrame, points: DataFrame, k: int, n_pivots: int = 16, sample: int = 2048, stage: str | None = None) -> DataFrame:
    """Voronoi cells around k-means pivots on both sides. A query cell's bound is the smallest that k points, taken by cells'
    pivot distances, surely lie within; a point goes to every query cell that it might serve by the triangle inequality.
    stage: a folder through which the two steps pass, as systems that write between steps do."""
    pts = q.orderBy(F.xxhash64("qid")).limit(sample).select("cx", "cy").toPandas().to_numpy(float)
    if not len(pts):
        return points.limit(0).select(F.lit(0).cast("long").alias("qid"), "pid", F.lit(0.0).alias("dist2"), F.lit(1).alias("rank"))
    b = kernels.pivot_blocks(pts[:, 0], pts[:, 1], n_pivots)
    pivots = np.array([pts[b.order[s:e]].mean(0) for s, e in zip(b.start, b.start[1:])])
    gap = np.sqrt(((pivots[:, None] - pivots[None]) ** 2).sum(2))

    @F.pandas_udf("struct<cell:int,d:double>")
    def nearest(x: pd.Series, y: pd.Series) -> pd.DataFrame:
        p = np.column_stack([x, y])
        c = kernels.nearest_pivot(p, pivots)
        return pd.DataFrame({"cell": c.astype("int32"), "d": np.sqrt(((p - pivots[c]) ** 2).sum(1))})

    asks = q.withColumn("_n", nearest("cx", "cy")).select("qid", "cx", "cy", F.col("_n.cell").alias("qcell"), F.col("_n.d").alias("qd"))
    has = points.select("pid", "x", "y").withColumn("_n", nearest("x", "y")).select("pid", "x", "y", F.col("_n.cell").alias("dcell"), F.col("_n.d").alias("dd"))
    if stage:
        asks.write.mode("overwrite").parquet(f"{stage}/asks")
        has.write.mode("overwrite").parquet(f"{stage}/has")
        asks, has = (points.sparkSession.read.parquet(f"{stage}/{n}") for n in ("asks", "has"))
    small = merge.topk(has.select(F.col("dcell").alias("qid"), "pid", "x", "y", F.col("dd").alias("dist2")), k)
    reach: dict[int, list[float]] = {}
    for r in small.collect():  # k rows a pivot
        reach.setdefault(r["qid"], []).append(r["dist2"])
    radius = {r["qcell"]: r["r"] for r in asks.groupBy("qcell").agg(F.max("qd").alias("r")).collect()}  # a row a pivot
    theta = {}
    for c, u in radius.items():
        far = np.sort(np.concatenate([gap[c, d] + np.array(v) for d, v in reach.items()])) if reach else np.zeros(0)
        theta[c] = u + far[k - 1] if len(far) >= k else np.inf
    pairs = [(int(c), *map(float, pivots[c]), float(radius[c] + theta[c])) for c in sorted(radius)]
    serves = lambda p: dist2(F.col("x"), F.col("y"), F.lit(p[1]), F.lit(p[2])) <= p[3] ** 2 * (1 + 1e-12) + 1e-9
    copies = has.select("pid", "x", "y", F.explode(F.array_compact(F.array(*(F.when(serves(p), F.lit(p[0])) for p in pairs)))).alias("tile"))
    routed = asks.withColumnRenamed("qcell", "tile")
    return merge.topk(knnjoin.local_knn(copies, routed, k, "hilbert_block"), k)


def datarep_distance_join(q: DataFrame, tt: TiledTable, half: float, opt: bool = False) -> DataFrame:
    """Square windows of one half-width around focal points: the data are copied to the tiles of the queries. opt: tiles that hold too many
    queries are cut first, and queries that the filters find nothing for neither stay nor draw copies of data."""
    w = q.select("qid", (F.col("cx") - half).alias("x1"), (F.col("cy") - half).alias("y1"), (F.col("cx") + half).alias("x2"), (F.col("cy") + half).alias("y2"))
    if opt:
        tt = tt if tt.filters is not None else tt.with_filters()
        w = route.ranges(w, tt.tiles, tt.filters).select("qid", "x1", "y1", "x2", "y2").distinct()
        tt = planned(w, tt)
    return range_join(w, tt, strategy="replicate_inner")


def datarep_knn(q: DataFrame, tt: TiledTable, k: int, opt: bool = False, sample: int = 1024) -> DataFrame:
    """A bound from a sample of the focal points, then one round. opt: tiles that hold too many focal points are cut, and filters prune."""
    return knnjoin.knn_join(q, tt, k, bound="sample", sample=sample, filter=opt, plan="query" if opt else None)


# point filters and index probes -----------------------------------------------------------------


class Bloom:
    """A Bloom filter of points: answers point membership only, never ranges."""

    def __init__(self, n: int, rate: float = 0.01):
        self.m = max(64, int(-n * np.log(rate) / np.log(2) ** 2))
        self.k = max(1, round(self.m / max(n, 1) * np.log(2)))
        self.bits = np.zeros(self.m // 8 + 1, np.uint8)

    def _at(self, x: np.ndarray, y: np.ndarray) -> Iterator[np.ndarray]:
        a = np.asarray(x, float).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ np.asarray(y, float).view(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
        a ^= a >> np.uint64(29)
        b = a * np.uint64(0xBF58476D1CE4E5B9) | np.uint64(1)
        for i in range(self.k):
            h = a + np.uint64(i) * b
            yield ((h ^ (h >> np.uint64(31))) % np.uint64(self.m)).astype(np.int64)

    def add(self, x: np.ndarray, y: np.ndarray) -> Bloom:
        for at in self._at(x, y):
            np.bitwise_or.at(self.bits, at >> 3, (1 << (at & 7)).astype(np.uint8))
        return self

    def may_contain(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for at in self._at(x, y):
            out &= (self.bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
        return out


def bloom_rows(points: DataFrame, probes: DataFrame, rate: float = 0.01) -> DataFrame:
    """(qid, maybe): probes (qid, cx, cy) against one Bloom filter of all points, built by partitions and united."""
    n = points.count()
    empty = Bloom(n, rate)

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = Bloom(n, rate)
        for b in batches:
            f.add(b.column("x").to_numpy(), b.column("y").to_numpy())
        yield pa.RecordBatch.from_arrays([pa.array([f.bits.tobytes()], pa.binary())], ["bits"])

    for r in points.select("x", "y").mapInArrow(part, "bits binary").toLocalIterator():
        empty.bits |= np.frombuffer(r["bits"], np.uint8)

    @F.pandas_udf("boolean")
    def maybe(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series(empty.may_contain(x.to_numpy(), y.to_numpy()))

    return probes.select("qid", maybe("cx", "cy").alias("maybe"))


def index_probe(kind: str, x: np.ndarray, y: np.ndarray, probes: np.ndarray) -> dict[str, float]:
    """Build time, time a probe, bytes and false positives of one structure on one tile: "obf", "obf_adaptive", "rtree", "quadtree", "bloom"."""
    truth = np.array([((x >= a) & (x <= c) & (y >= b) & (y <= d)).any() for a, b, c, d in probes])
    began = time.perf_counter()
    if kind in ("rtree", "quadtree"):
        blocks = (kernels.rtree_blocks if kind == "rtree" else kernels.quadtree_blocks)(x, y)
        tree = kernels.PackedTree.over(blocks.boxes)
        built = time.perf_counter()
        hit = np.zeros(len(probes), bool)
        for i, p in enumerate(probes):
            _, leaf = tree.leaves_meeting(p[None])
            for b in leaf:
                at = blocks.order[blocks.start[b] : blocks.start[b + 1]]
                if ((x[at] >= p[0]) & (x[at] <= p[2]) & (y[at] >= p[1]) & (y[at] <= p[3])).any():
                    hit[i] = True
                    break
        size = sum(v.nbytes for v in tree.levels) + blocks.order.nbytes + blocks.start.nbytes + x.nbytes + y.nbytes
    elif kind == "bloom":
        f = Bloom(len(x)).add(x, y)
        built = time.perf_counter()
        mid = (probes[:, :2] + probes[:, 2:]) / 2
        hit, truth = f.may_contain(mid[:, 0], mid[:, 1]), np.isin(mid[:, 0] + 1j * mid[:, 1], x + 1j * y)
        size = f.bits.nbytes
    else:
        f = obf.build(x, y, (float(x.min()), float(y.min()), float(x.max()), float(y.max())))
        if kind == "obf_adaptive":
            for p in probes[~truth][: len(probes) // 4]:
                f = obf.mark_empty(f, tuple(p), "exact", 9, (x, y))
            f = obf.shrink(f, max(f.size_bits // 2, 64))
        built = time.perf_counter()
        ones = f.prefix()
        hit = np.array([obf.may_contain(f, tuple(p), ones) for p in probes])
        size = f.size_bits / 8
    done = time.perf_counter()
    fp, tn, tp = (hit & ~truth).sum(), (~hit & ~truth).sum(), (hit & truth).sum()
    return {"build_s": built - began, "probe_ms": (done - built) * 1000 / max(1, len(probes)), "mb": size / 1e6, "fpr": float(fp / max(1, fp + tn)), "fdr": float(fp / max(1, fp + tp)), "false_negatives": int((truth & ~hit).sum())}


def distance_by_circle(q: DataFrame, points: DataFrame, r: float) -> DataFrame:
    """The theta join behind a distance join, for comparison."""
    return points.join(F.broadcast(_bounded(q)), in_circle(F.col("x"), F.col("y"), F.col("cx"), F.col("cy"), F.lit(r))).select("qid", "pid")


