"""Range and distance joins: queries are routed to the tiles of the data, joined there, and the answers united."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skewtile.functions.geometry import in_circle, in_rect
from skewtile.operators import local as kernels
from skewtile.operators import blocks, merge
from skewtile.operators.tiled import TiledTable
from skewtile.plans import route
from skewtile.plans.cost import CostModel, Tile, calibrate_sampled
from skewtile.plans.tilemap import TileMap, by_tile, sample_points

MAX_LEVEL, SAMPLED_WINDOWS = 16, 1024
Keep = Callable[..., np.ndarray]


@dataclass(frozen=True)
class Cells:
    """The sides of the join's cells: 4 ** step at level 0, times 4 a level; `levels` are those that some window takes."""

    step: int = 0
    levels: tuple[int, ...] = (0,)

    @classmethod
    def of(cls, q: DataFrame, tm: TileMap | None = None) -> Cells:
        """One job: windows by the size of cell that they would take, fewer than a thousand rows. Level 0 is the median window's; windows
        wider than the widest tile are cut to tiles, so they need no wider cells than those."""
        rows = q.select(_wanted(_extent()).alias("s")).groupBy("s").agg(F.count(F.lit(1)).alias("n")).orderBy("s").collect()
        sizes = [(r["s"], r["n"]) for r in rows if r["s"] is not None]
        if not sizes:
            return cls(0, (0,))
        steps, half = np.array([s for s, _ in sizes]), sum(n for _, n in sizes) / 2
        step = int(steps[np.searchsorted(np.cumsum([n for _, n in sizes]), half)])
        most = MAX_LEVEL
        if tm is not None:
            b = tm.data_boxes()
            side = np.nanmax(np.maximum(b[:, 2] - b[:, 0], b[:, 3] - b[:, 1]), initial=0.0)
            most = min(most, max(0, math.ceil(math.log(max(side, 1e-300) / 3, 4)) - step))
        return cls(step, tuple(sorted({int(min(max(s - step, 0), most)) for s, _ in sizes} | ({0} if any(r["s"] is None for r in rows) else set()))))

    def level(self) -> Column:
        """A window's level among those in use."""
        wish = F.least(F.greatest(_wanted(_extent()) - self.step, F.lit(self.levels[0])), F.lit(self.levels[-1]))
        at = F.lit(self.levels[-1])
        for one in reversed(self.levels[:-1]):
            at = F.when(wish <= one, one).otherwise(at)
        return F.coalesce(at, F.lit(self.levels[0])).cast("int")

    def side(self) -> Column:
        return F.pow(F.lit(4.0), F.col("level") + self.step)


def _extent() -> Column:
    return F.greatest(F.col("x2") - F.col("x1"), F.col("y2") - F.col("y1"))


def _wanted(extent: Column) -> Column:
    """The power of four of the cell side that a window of this extent covers at most four of; null for points."""
    return F.when(extent > 0, F.ceil(F.log(4.0, extent / 3)).cast("int"))


def cell_join(data: DataFrame, routed: DataFrame, cells: Cells, tm: TileMap | None = None) -> DataFrame:
    """Local joins as one equi-join on (slot, tile, cell) with the window left over. Points have one cell a size, so no pair comes
    twice. Where both sides have slots, data that lie by slot are left where they are."""
    d, q, keys = cell_keyed(data, routed, cells, tm)
    return d.join(q, keys).where(in_rect(F.col("x"), F.col("y"), F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2")))


def cell_keyed(data: DataFrame, routed: DataFrame, cells: Cells, tm: TileMap | None = None) -> tuple[DataFrame, DataFrame, list[str]]:
    """Both sides with the keys that they meet on. A window takes the cell size at which it covers few
    cells; data are keyed at each size in use. With a tile map, windows are cut to their tile's data first."""
    ends = [F.col(c) for c in ("x1", "y1", "x2", "y2")]
    q = routed.withColumn("level", cells.level())
    if tm is not None:
        box = tm.data_boxes()
        edge = [by_tile(box[:, k].tolist(), F.col("tile"), "double") for k in range(4)]
        ends = [F.greatest(ends[0], edge[0]), F.greatest(ends[1], edge[1]), F.least(ends[2], edge[2]), F.least(ends[3], edge[3])]
    steps = lambda lo, hi: F.explode(F.sequence(F.floor(lo / cells.side()), F.greatest(F.floor(hi / cells.side()), F.floor(lo / cells.side()))))
    q = q.withColumn("_cx", steps(ends[0], ends[2])).withColumn("_cy", steps(ends[1], ends[3]))
    d = data.withColumn("level", F.lit(cells.levels[0]) if len(cells.levels) == 1 else F.explode(F.array(*map(F.lit, cells.levels))))
    d = d.withColumn("_cx", F.floor(F.col("x") / cells.side())).withColumn("_cy", F.floor(F.col("y") / cells.side()))
    keys = [c for c in ("slot", "tile") if c in data.columns and c in routed.columns] + ["level", "_cx", "_cy"]
    return d, q, keys


def kernel_join(data: DataFrame, routed: DataFrame, algo: str, tt: TiledTable, timed: bool = False, keep: Keep | None = None, carry: tuple[str, ...] = ()) -> DataFrame:
    """Local joins by one of the numpy kernels: (qid, pid). A tile is dealt out in parts of bounded size (see `blocks`); a task indexes a part's
    data and streams its windows past them, and pairs leave in pieces. keep: an exact test of pairs, on x, y and the columns of routed named
    in carry; where there is none, x, y and the carried columns come out too. timed: one row a tile instead,
    (tile, n_data, n_query, pairs, seconds). tt: the table whose rows these are."""

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        began = time.perf_counter()
        pid, x, y, windows = blocks.first_side(batches, ("id", "x1", "y1"))
        ask, n_query, n_pairs = None, 0, 0
        for b in windows if len(pid) else ():
            rects = np.column_stack([b.column(c).to_numpy() for c in ("x1", "y1", "x2", "y2")])
            if ask is None:
                ask = kernels.PROBES[kernels.choose("point", len(x), len(rects)) if algo == "auto" else algo](x, y)
            n_query += len(rects)
            qid, more = b.column("id").to_numpy(), [b.column(c).to_numpy() for c in carry]
            for q, i in ask(rects):
                n_pairs += len(q)
                if timed or not len(q):
                    continue
                own = [m[q] for m in more]
                if keep is not None:
                    yes = keep(x[i], y[i], *own)
                    yield pa.RecordBatch.from_arrays([pa.array(qid[q][yes]), pa.array(pid[i][yes])], ["qid", "pid"])
                else:
                    yield pa.RecordBatch.from_arrays([pa.array(v) for v in ((qid[q], pid[i], x[i], y[i], *own) if carry else (qid[q], pid[i]))], names)
        if timed:
            tile, part, share = (k.as_py() for k in key[-3:])
            yield pa.RecordBatch.from_arrays([pa.array([v]) for v in (tile, part, share, len(pid), n_query, n_pairs, time.perf_counter() - began)], ["tile", "part", "share", "n_data", "n_query", "pairs", "seconds"])

    schema = "qid long, pid long" + ("" if keep is not None or not carry else ", x double, y double" + "".join(f", {c} double" for c in carry))
    names = [c.split()[0] for c in schema.split(", ")]
    slot = [c for c in ("slot",) if c in data.columns and c in routed.columns]
    data = data.select(*slot, "tile", F.col("pid").cast("long").alias("id"), F.col("x").cast("double").alias("x1"), F.col("y").cast("double").alias("y1"))
    routed = routed.select(*slot, "tile", F.col("qid").cast("long").alias("id"), *(F.col(c).cast("double").alias(c) for c in dict.fromkeys(("x1", "y1", "x2", "y2", *carry))))
    dealt = blocks.dealt(data, routed, tt.counts, slot, tt.n_slots)
    if not timed:
        return dealt.applyInArrow(run, schema)
    rows = dealt.applyInArrow(run, "tile long, part long, share long, n_data long, n_query long, pairs long, seconds double")
    once = lambda c, by: F.sum(F.when(F.col(by) == 0, F.col(c))).cast("long").alias(c)
    return rows.groupBy("tile").agg(once("n_data", "share"), once("n_query", "part"), F.sum("pairs").alias("pairs"), F.sum("seconds").alias("seconds")).where("n_data > 0 AND n_query > 0")


def range_join(
    q: DataFrame, tt: TiledTable, local: str = "catalyst", filter: bool = False, plan: str | None = None, budget: int = 8,
    mode: str = "minimal", how: str = "inner", strategy: str = "replicate_queries", residual: Column | None = None, cells: Cells | None = None, dedup: bool = False,
    carry: tuple[str, ...] = (), model: CostModel | None = None, keep: Keep | None = None,
) -> DataFrame:
    """(qid, pid) of all points in each closed window (qid, x1, y1, x2, y2). Windows that end before they begin hold nothing.

    local: "catalyst" (equi-join on cells), a kernel's name, or "auto". filter: prune routed windows by occupancy filters.
    plan: None, or "query", "data", "product", "sampled", "calibrated" (split skewed tiles; see `planned`).
    how: inner, left (windows without answers keep a null pid), semi or anti (their qid only). strategy: "replicate_inner"
    copies the data to the windows' tiles instead. dedup: identical windows are searched once and given back to all.
    residual: a further predicate over x, y and the columns of q named in carry; keep: the same on arrays, for kernels. model: the plan's cost
    model."""
    whole = q
    q = q.select("qid", "x1", "y1", "x2", "y2", *carry).where("x1 <= x2 AND y1 <= y2")
    if dedup:
        one = q.groupBy("x1", "y1", "x2", "y2", *carry).agg(F.min("qid").alias("_one"))
        same = ["x1", "y1", "x2", "y2", *carry]
        names = q.join(one, same).select("qid", "_one")
        found = range_join(one.withColumnRenamed("_one", "qid"), tt, local, filter, plan, budget, mode, "inner", strategy, residual, cells, False, carry, model, keep)
        pairs = found.withColumnRenamed("qid", "_one").join(names, "_one").select("qid", "pid")
        return finish(whole, pairs, how)
    if strategy == "replicate_inner":
        return finish(whole, _replicate_inner(q, tt, cells or Cells.of(q), residual), how)
    if filter and tt.filters is None:
        tt = tt.with_filters()
    if plan:
        tt = planned(q, tt, plan, budget, mode, model)
    routed = tt.place(route.ranges(q, tt.tiles, tt.filters if filter else None))
    if local == "catalyst" and cells is None:
        cells = Cells.of(q, tt.tiles)
    out = []
    for i, part in enumerate(tt.parts):
        asked = tt.of_part(routed, i)
        if local == "catalyst":
            got = cell_join(part.select("pid", "x", "y", *tt.keys), asked, cells, tt.tiles)
        else:
            got = kernel_join(tt.visited(part, asked), asked, local, tt, keep=keep, carry=carry)
        if residual is not None and (local == "catalyst" or keep is None):
            got = got.where(residual)
        out.append(got.select("qid", "pid"))
    return finish(whole, merge.union(out), how)


def planned(q: DataFrame, tt: TiledTable, by: str = "query", budget: int = 8, mode: str = "minimal", model: CostModel | None = None) -> TiledTable:
    """The table with the tiles cut that these windows skew, by the cost model. A batch that is planned alike takes the split made
    before. by: what the cuts halve; "sampled" and "calibrated" halve queries and estimate local work from samples of both sides, the
    latter with weights from the timed local joins of a sample of the windows."""
    q, pairs = q.select("qid", "x1", "y1", "x2", "y2"), None
    if by in ("sampled", "calibrated"):
        pairs = sampled_pairs(q, tt)
        if model is None:
            some = q.orderBy(F.xxhash64("qid")).limit(SAMPLED_WINDOWS)
            model = CostModel(p_probe=1.0, p_pair=1.0) if by == "sampled" else calibrated(some, tt)
        by = "query"
    return tt.apply(tt.plan(route.ranges(q, tt.tiles), budget, by, mode, model or CostModel(), pairs))


def sampled_pairs(q: DataFrame, tt: TiledTable, n_data: int = 8192, n_query: int = SAMPLED_WINDOWS) -> np.ndarray:
    """The answers expected of each tile, from samples of bounded size of both sides."""
    data = sample_points(tt.rows, n_data)
    n = q.count()
    boxes = q.orderBy(F.xxhash64("qid")).limit(n_query).select("x1", "y1", "x2", "y2").toPandas().to_numpy(float)
    if not len(data) or not len(boxes):
        return np.zeros(tt.tiles.n_tiles)
    inside = (data[:, 0] >= boxes[:, :1]) & (data[:, 0] <= boxes[:, 2:3]) & (data[:, 1] >= boxes[:, 1:2]) & (data[:, 1] <= boxes[:, 3:])
    held = np.bincount(tt.tiles.locate(data[:, 0], data[:, 1]), weights=inside.sum(0), minlength=tt.tiles.n_tiles)
    return held * (tt.n_rows / len(data)) * (n / len(boxes))


def tile_times(q: DataFrame, tt: TiledTable, local: str = "auto", filter: bool = False) -> DataFrame:
    """(tile, n_data, n_query, pairs, seconds) of every tile's local join, out of the tasks that ran them."""
    routed = tt.place(route.ranges(q.select("qid", "x1", "y1", "x2", "y2"), tt.tiles, tt.filters if filter else None))
    return merge.union([kernel_join(part, tt.of_part(routed, i), local, tt, timed=True) for i, part in enumerate(tt.parts)])


def calibrated(q: DataFrame, tt: TiledTable, local: str = "auto", records_per_second: float = 1e6) -> CostModel:
    """Weights in seconds from the timed local joins of a batch: a row a tile comes to the driver."""
    rows = tile_times(q, tt, local).collect()
    return calibrate_sampled([(Tile(r["n_data"], r["n_query"], r["pairs"]), r["seconds"]) for r in rows], records_per_second) if rows else CostModel()


def finish(q: DataFrame, pairs: DataFrame, how: str) -> DataFrame:
    if how == "inner":
        return pairs
    if how == "left":
        return q.select("qid").join(pairs, "qid", "left")
    return q.select("qid").join(pairs.select("qid").distinct() if how == "semi" else pairs, "qid", f"left_{how}")


def _replicate_inner(q: DataFrame, tt: TiledTable, cells: Cells, residual: Column | None = None) -> DataFrame:
    """The other way round: windows stay in the tile of their middle, and data go to every tile whose windows may hold them. The map
    finds the tiles near a point as far as windows reach out of theirs; each tile's windows' common box decides."""
    placed = q.withColumn("tile", tt.tiles.tile_of((F.col("x1") + F.col("x2")) / 2, (F.col("y1") + F.col("y2")) / 2))
    mbr = np.full((tt.tiles.n_tiles, 4), np.nan)
    for t, *b in placed.groupBy("tile").agg(F.min("x1"), F.min("y1"), F.max("x2"), F.max("y2")).collect():  # a row a tile
        mbr[t] = b
    used = ~np.isnan(mbr[:, 0])
    if not used.any():
        return tt.df.limit(0).select(F.lit(0).cast("long").alias("qid"), "pid")
    reach = tt.tiles.with_mbr(np.where(used[:, None], mbr, np.nan))
    region = tt.tiles.boxes()[used]
    out = [float(max(0.0, np.max(np.maximum(region[:, k] - mbr[used, k], mbr[used, k + 2] - region[:, k + 2])))) for k in (0, 1)]
    near = reach.with_mbr(None).tiles_in_reach(F.col("x"), F.col("y"), *out)
    edge = [by_tile(mbr[:, k].tolist(), F.col("tile"), "double") for k in range(4)]
    copies = tt.rows.select("pid", "x", "y", F.explode(near).alias("tile")).where(~F.isnan(edge[0]) & in_rect(F.col("x"), F.col("y"), *edge))
    got = cell_join(copies, placed, cells)
    return (got if residual is None else got.where(residual)).select("qid", "pid")


def distance_join(q: DataFrame, tt: TiledTable, r: float | None = None, **options) -> DataFrame:
    """(qid, pid) of all points within distance r of each focal point (qid, cx, cy); r None: a column r of q. The test is on the given
    coordinates and radius; windows around them, a little too wide, only find the candidates."""
    radius = F.col("r") if r is None else F.lit(float(r))
    reach = F.col("_r") + (F.abs("cx") + F.abs("cy") + F.col("_r")) * 1e-14
    w = q.select("qid", F.col("cx").cast("double").alias("cx"), F.col("cy").cast("double").alias("cy"), radius.cast("double").alias("_r"))
    w = w.select("*", (F.col("cx") - reach).alias("x1"), (F.col("cy") - reach).alias("y1"), (F.col("cx") + reach).alias("x2"), (F.col("cy") + reach).alias("y2"))
    near = in_circle(F.col("x"), F.col("y"), F.col("cx"), F.col("cy"), F.col("_r")) & (F.col("_r") >= 0)
    return range_join(w, tt, residual=near, keep=_in_disc, carry=("cx", "cy", "_r"), **options)


def _in_disc(x: np.ndarray, y: np.ndarray, cx: np.ndarray, cy: np.ndarray, r: np.ndarray) -> np.ndarray:
    dx, dy = x - cx, y - cy
    return (x >= cx - r) & (x <= cx + r) & (y >= cy - r) & (y <= cy + r) & (dx * dx + dy * dy <= r * r) & (r >= 0)


def self_range_join(points: DataFrame, tt: TiledTable, half: float, **options) -> DataFrame:
    """Pairs (qid, pid), qid <> pid, of points in each other's window."""
    w = points.select(F.col("pid").alias("qid"), (F.col("x") - half).alias("x1"), (F.col("y") - half).alias("y1"), (F.col("x") + half).alias("x2"), (F.col("y") + half).alias("y2"))
    return range_join(w, tt, **options).where("qid <> pid")


def salted_join(q: DataFrame, tt: TiledTable, salts: int = 8, cells: Cells | None = None) -> DataFrame:
    """For hot spots that no cut divides (many points in one place): windows are copied to every salt, points are dealt to one."""
    cells = cells or Cells.of(q)
    routed = route.ranges(q, tt.tiles).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    data = tt.rows.select("pid", "x", "y", (F.col("tile") * salts + F.pmod(F.xxhash64("pid"), F.lit(salts))).cast("long").alias("tile"))
    routed = routed.withColumn("tile", (F.col("tile") * salts + F.col("salt")).cast("long")).drop("salt")
    return cell_join(data, routed, cells).select("qid", "pid")


def aqe_join(q: DataFrame, tt: TiledTable) -> DataFrame:
    """What a planner without costs of tiles does: tiles meet their windows by tile number alone, and skew is left to Spark, which splits
    large partitions of a sort-merge join while it runs."""
    routed = route.ranges(q.select("qid", "x1", "y1", "x2", "y2"), tt.tiles)
    hits = tt.rows.select("pid", "x", "y", "tile").hint("merge").join(routed, "tile")
    return hits.where(in_rect(F.col("x"), F.col("y"), F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"))).select("qid", "pid")


def empty_probes(q: DataFrame, tt: TiledTable) -> DataFrame:
    """(tile, x1, y1, x2, y2): routed windows that had no answer in that tile, which is what filters learn from."""
    q = q.select("qid", "x1", "y1", "x2", "y2")
    routed = route.ranges(q, tt.tiles, tt.filters)
    hits = cell_join(tt.rows.select("pid", "x", "y", "tile"), routed, Cells.of(q, tt.tiles), tt.tiles).select("qid", "tile").distinct()
    return routed.join(hits, ["qid", "tile"], "left_anti").select("tile", "x1", "y1", "x2", "y2")


def adapt(q: DataFrame, tt: TiledTable, border: str = "exact", max_depth: int = 9, max_bits: int | None = None, policy: str = "deepest") -> TiledTable:
    """One round of learning: the table with filters refreshed by what these windows found empty."""
    tt = tt if tt.filters is not None else tt.with_filters()
    return tt.like(filters=tt.filters.refresh(tt.rows, empty_probes(q, tt), border, max_depth, max_bits, policy))


def modelled_costs(q: DataFrame, tt: TiledTable, budget: int = 8, by: str = "query", model: CostModel = CostModel(), pairs: np.ndarray | None = None) -> list[float]:
    """The plan's cost before and after each split."""
    return tt.plan(route.ranges(q, tt.tiles), budget, by, model=model, pairs=pairs).costs
