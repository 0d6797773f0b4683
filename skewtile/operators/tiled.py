"""Tiled tables: points with their tile, a placement slot and a cell code, laid out once and reused by every batch of queries."""

from __future__ import annotations

import json
from dataclasses import dataclass, field, replace
from functools import cached_property, reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from skewtile.functions.curves import morton_column
from skewtile.plans import planner
from skewtile.plans.cost import CostModel, Tile
from skewtile.plans.filterstore import ROW, FilterStore, build_rows, from_row, to_row
from skewtile.plans.tilemap import TileMap, build_map, by_tile

CELLS = 16
"""Sub-cells a side on which a skewed tile's data and queries are counted before it is cut."""
SKEW = 1.5
"""Tiles whose work is above so many times the median's are candidates for a split; where none is, nothing is cut."""
PLANNED_AT_ONCE = 1024
"""Maps of up to so many tiles have all routed queries counted on sub-cells in one job."""


def slot_keys(spark: SparkSession, n: int) -> list[int]:
    """For each of n partitions, the smallest integer that hash partitioning sends there."""
    got = (
        spark.range(0, max(64, 40 * n)).select(F.col("id").cast("int").alias("key")).withColumn("p", F.pmod(F.hash("key"), F.lit(n)))
        .groupBy("p").agg(F.min("key").alias("key")).orderBy("p").collect()
    )
    if len(got) < n:
        raise ValueError(f"no key found for some of {n} partitions")
    return [r["key"] for r in got]


def pack(weights: np.ndarray, n_slots: int) -> np.ndarray:
    """Tiles to slots, heaviest first into the lightest slot."""
    load, slot = np.zeros(n_slots), np.zeros(len(weights), np.int64)
    for t in np.argsort(-weights, kind="stable"):
        slot[t] = load.argmin()
        load[slot[t]] += weights[t]
    return slot


CO_PARTITION = "spark.sql.requireAllClusterKeysForCoPartition"
SAMPLE_PER_TILE, BROADCAST_TILES = 128, 1 << 20
FINEST = 7
"""Levels of cells, each a fourth as wide as the one before, whose counts bound nearest neighbours."""


@dataclass(frozen=True)
class TiledTable:
    """df has pid, x, y, the payload, and tile; laid_out() adds slot and cell. Counts are those of each tile's rows. After a split, more has the
    rows of the tiles that were cut, which alone were moved; all are under one map, and lies_in tells each tile's part."""

    df: DataFrame
    tiles: TileMap
    counts: np.ndarray
    n_slots: int
    filters: FilterStore | None = None
    more: tuple[DataFrame, ...] = ()
    own_slots: tuple[int, ...] | None = None
    lies_in: tuple[int, ...] = ()
    memo: dict = field(default_factory=dict, compare=False, repr=False)
    """Counts of sub-cells and splits already made, for the batches that follow."""

    @classmethod
    def build(cls, df: DataFrame, n_tiles: int = 16, kind: str = "kd", sample: int | None = None, n_slots: int | None = None, tile_map: TileMap | None = None, with_filters: bool = False, max_depth: int = 7) -> TiledTable:
        """Rows with null or NaN coordinates have no place and are left out."""
        df = df.where(F.col("x").isNotNull() & F.col("y").isNotNull() & ~F.isnan("x") & ~F.isnan("y"))
        tm = tile_map or build_map(df, n_tiles, kind, sample or max(4096, SAMPLE_PER_TILE * n_tiles))
        tiled = df.withColumn("tile", tm.tile_of(F.col("x"), F.col("y")))
        tm, counts = measure(tiled, tm)
        out = cls(tiled, tm, counts, n_slots or min(tm.n_tiles, df.sparkSession.sparkContext.defaultParallelism))
        return out.with_filters(max_depth) if with_filters else out

    def with_filters(self, max_depth: int = 7, leaf_cap: int = 1) -> TiledTable:
        return self.like(filters=FilterStore.collect(build_rows(self.rows, self.tiles, max_depth, leaf_cap), self.tiles.n_tiles))

    def like(self, **changes) -> TiledTable:
        """This table with changes; the counts of sub-cells go with it, splits made before don't."""
        return replace(self, memo={"cells": self.memo.setdefault("cells", {})}, **changes)

    @property
    def n_rows(self) -> int:
        return int(self.counts.sum())

    @property
    def parts(self) -> list[DataFrame]:
        """The rows that stayed in place, and those that a split moved: joins take each where it lies."""
        return [self.df, *self.more]

    @property
    def rows(self) -> DataFrame:
        return reduce(DataFrame.unionByName, self.parts)

    @property
    def keys(self) -> list[str]:
        """What joins meet on: the slot too, once the rows are laid out by it."""
        return ["slot", "tile"] if "slot" in self.df.columns else ["tile"]

    @cached_property
    def slots(self) -> list[int]:
        if self.own_slots is not None:
            return list(self.own_slots)
        keys = slot_keys(self.df.sparkSession, self.n_slots)
        return [keys[s] for s in pack(self.counts.astype(float), self.n_slots)]

    def of_part(self, routed: DataFrame, part: int) -> DataFrame:
        """The routed queries whose tile lies in that part."""
        return routed.where(by_tile(list(self.lies_in), F.col("tile"), "int") == part) if self.more else routed

    def visited(self, part: DataFrame, asked: DataFrame) -> DataFrame:
        """The rows of the tiles that some query was sent to, where they lie: what a Python kernel is worth being given. The tiles' numbers are
        broadcast if the map has few enough."""
        if self.tiles.n_tiles > BROADCAST_TILES:
            return part
        return part.join(F.broadcast(asked.select("tile").distinct()), "tile", "left_semi")

    def place(self, routed: DataFrame) -> DataFrame:
        """Routed queries with the slot of their tile, if the table has slots."""
        return routed.withColumn("slot", by_tile(self.slots, F.col("tile"), "int")) if "slot" in self.df.columns else routed

    def laid_out(self, persist: bool = False) -> TiledTable:
        """Places every tile in its slot's partition, sorted by tile and Morton cell; joins on slot and tile then leave the data where they
        are, for which the session is told that a partitioning by some of a join's keys is enough."""
        self.df.sparkSession.conf.set(CO_PARTITION, "false")
        x1, y1, x2, y2 = self.tiles.bounds
        grid = lambda c, lo, hi: F.least(F.greatest(F.floor((F.col(c) - lo) / max(hi - lo, 1e-300) * 65535), F.lit(0)), F.lit(65535))
        df = self.rows.withColumn("slot", by_tile(self.slots, F.col("tile"), "int")).withColumn("cell", morton_column(grid("x", x1, x2), grid("y", y1, y2)))
        df = df.repartition(self.n_slots, "slot").sortWithinPartitions("tile", "cell")
        return self.like(df=df.persist() if persist else df, more=(), lies_in=(), own_slots=tuple(self.slots))

    @property
    def frame(self) -> tuple[float, float, float, float]:
        """The box of all data."""
        b = self.tiles.data_boxes()[self.counts > 0]
        return (*map(float, b[:, :2].min(0)), *map(float, b[:, 2:].max(0))) if len(b) else (0.0, 0.0, 0.0, 0.0)

    def fine(self, x: Column, y: Column) -> list[Column]:
        """The column and row of a place among the finest cells of the frame."""
        x1, y1, x2, y2 = self.frame
        step = max(x2 - x1, y2 - y1, 1e-300) / 4**FINEST
        return [F.least(F.greatest(F.floor((v - lo) / step), F.lit(-(1 << 40))), F.lit(1 << 40)) for v, lo in ((x, x1), (y, y1))]

    def cell_counts(self) -> DataFrame:
        """(level, gx, gy, n, x1, y1, x2, y2): counts and tight boxes of the occupied cells of all levels, level 1 the widest: the
        finest are counted from the rows, and the wider ones from those."""
        gx, gy = self.fine(F.col("x"), F.col("y"))
        low = self.rows.groupBy(gx.alias("gx"), gy.alias("gy")).agg(F.count(F.lit(1)).alias("n"), F.min("x").alias("x1"), F.min("y").alias("y1"), F.max("x").alias("x2"), F.max("y").alias("y2"))
        low = low.withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(FINEST))))
        up = lambda c: F.call_function("shiftright", F.col(c), 2 * (FINEST - F.col("level"))).alias(c)
        return low.groupBy("level", up("gx"), up("gy")).agg(F.sum("n").alias("n"), F.min("x1").alias("x1"), F.min("y1").alias("y1"), F.max("x2").alias("x2"), F.max("y2").alias("y2"))

    def stats(self) -> DataFrame:
        """One row per tile: its region, its data's box and count."""
        b, m = self.tiles.finite_boxes(), self.tiles.mbr
        rows = [(t, *map(float, b[t]), *(None if np.isnan(v) else float(v) for v in m[t]), int(self.counts[t])) for t in range(self.tiles.n_tiles)]
        return self.df.sparkSession.createDataFrame(rows, "tile int, x1 double, y1 double, x2 double, y2 double, mx1 double, my1 double, mx2 double, my2 double, n_data long")

    def save(self, path: str) -> None:
        """Parquet partitioned by tile, sorted by cell within it, and the map, counts, slots and filters beside it."""
        out = self.laid_out()
        out.df.write.mode("overwrite").partitionBy("tile").parquet(f"{path}/rows")
        out._save_map(path)

    def _save_map(self, path: str) -> None:
        spark = self.df.sparkSession
        meta = json.dumps({"map": self.tiles.to_json(), "counts": self.counts.tolist(), "n_slots": self.n_slots, "slots": list(map(int, self.slots))})
        spark.createDataFrame([(meta,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/map")
        kept = [to_row(t, f) for t, f in self.filters.filters.items()] if self.filters is not None else []
        spark.createDataFrame(kept, ROW).coalesce(1).write.mode("overwrite").parquet(f"{path}/filters")

    @classmethod
    def load(cls, spark: SparkSession, path: str, rows: DataFrame | None = None) -> TiledTable:
        """The saved table; its rows have their slots, and lie by tile until laid_out() is called again. rows: a bucketed table in their place."""
        meta = json.loads(spark.read.text(f"{path}/map").first()[0])
        filters = {r["tile"]: from_row(r) for r in spark.read.parquet(f"{path}/filters").collect()}  # a bounded row a tile
        store = FilterStore(filters) if filters else None
        df = spark.read.parquet(f"{path}/rows") if rows is None else rows
        return cls(df, TileMap.from_json(meta["map"]), np.array(meta["counts"]), meta["n_slots"], store, own_slots=tuple(meta["slots"]))

    def save_bucketed(self, name: str, path: str) -> None:
        """The durable layout: a table bucketed by slot, on which joins need no exchange, and the map under path."""
        out = self.laid_out()
        out.df.write.mode("overwrite").bucketBy(self.n_slots, "slot").sortBy("cell").saveAsTable(name)
        out._save_map(path)

    @classmethod
    def load_bucketed(cls, spark: SparkSession, name: str, path: str) -> TiledTable:
        spark.conf.set(CO_PARTITION, "false")
        return cls.load(spark, path, spark.table(name))

    # splitting ----------------------------------------------------------------------------------

    def _cells(self, df: DataFrame, x: Column, y: Column) -> DataFrame:
        """(tile, gx, gy, n): rows on CELLS x CELLS sub-cells of their tile's data box."""
        boxes = np.nan_to_num(self.tiles.data_boxes())
        edge = [by_tile(boxes[:, k].tolist(), F.col("tile"), "double") for k in range(4)]
        at = lambda v, lo, hi: F.least(F.greatest(F.floor((v - lo) / F.greatest(hi - lo, F.lit(1e-300)) * CELLS), F.lit(0)), F.lit(CELLS - 1)).cast("int")
        return df.groupBy("tile", at(x, edge[0], edge[2]).alias("gx"), at(y, edge[1], edge[3]).alias("gy")).agg(F.count(F.lit(1)).alias("n"))

    def _data_cells(self, tiles: list[int]) -> dict[int, np.ndarray]:
        """Data counts on sub-cells, counted once a tile and kept."""
        known = self.memo.setdefault("cells", {})
        if new := [t for t in tiles if t not in known]:
            for t in new:
                known[t] = np.zeros((CELLS, CELLS))
            for r in self._cells(self.rows.where(F.col("tile").isin(new)), F.col("x"), F.col("y")).collect():  # CELLS squared rows a tile
                known[r["tile"]][r["gx"], r["gy"]] = r["n"]
        return {t: known[t] for t in tiles}

    def plan(self, routed: DataFrame, budget: int, by: str = "query", mode: str = "minimal", model: CostModel = CostModel(), pairs: np.ndarray | None = None, **rules) -> planner.SplitPlan:
        """The greedy plan for these routed queries (tile, x1, y1, x2, y2). Handles of unsplit light tiles are their numbers, of heavy ones
        histograms. pairs: the answers expected of each tile, where the model asks for them."""
        middle = ((F.col("x1") + F.col("x2")) / 2, (F.col("y1") + F.col("y2")) / 2)
        n = self.tiles.n_tiles
        asked, query = np.zeros(n), {}
        if n <= PLANNED_AT_ONCE:
            for r in self._cells(routed, *middle).collect():  # CELLS squared rows a tile, few tiles
                asked[r["tile"]] += r["n"]
                query.setdefault(r["tile"], np.zeros((CELLS, CELLS)))[r["gx"], r["gy"]] = r["n"]
        else:
            for r in routed.groupBy("tile").agg(F.count(F.lit(1)).alias("n")).collect():  # a row a tile
                asked[r["tile"]] = r["n"]
        expect = [None if pairs is None else float(pairs[t]) for t in range(n)]
        tiles = [Tile(float(self.counts[t]), float(asked[t]), expect[t]) for t in range(n)]
        work = np.array([model.local(t) for t in tiles])
        skewed = planner.classify(tiles, model, SKEW)
        heavy = [int(t) for t in np.argsort(-work, kind="stable")[: max(1, budget)] if work[t] > 0 and skewed[t]]
        if n > PLANNED_AT_ONCE:
            for r in self._cells(routed.where(F.col("tile").isin(heavy)), *middle).collect():  # CELLS squared rows a tile, heavy tiles only
                query.setdefault(r["tile"], np.zeros((CELLS, CELLS)))[r["gx"], r["gy"]] = r["n"]
        boxes, data = self.tiles.data_boxes(), self._data_cells(heavy) if heavy else {}
        empty = np.zeros((CELLS, CELLS))
        hist = {t: planner.Histogram(tuple(map(float, boxes[t])), data[t], query.get(t, empty), expect[t]) for t in heavy}
        handles = [(hist.get(t, t), tiles[t]) for t in range(n)]
        cut = planner.cutter(by)
        plan = planner.greedy(handles, lambda h, k: cut(h, k) if isinstance(h, planner.Histogram) else [], budget, model, mode, **rules)
        number = {id(h): t for t, (h, _) in enumerate(handles)}
        plan.splits = {number[id(h)]: parts for h, parts in _by_identity(plan, handles)}
        return plan

    def apply(self, plan: planner.SplitPlan) -> TiledTable:
        """The table under the map with the plan's cuts. Rows of cut tiles alone get new places; all others stay as they are laid out,
        under their tiles' new numbers. A split that was made before is taken again."""
        trees = {t: planner.graft(None, [h for h, _ in parts]) for t, parts in plan.splits.items() if len(parts) > 1}
        if not trees:
            return self
        made = self.memo.setdefault("splits", {})
        if (key := repr(sorted(trees.items()))) not in made:
            made[key] = self._split(trees)
        return made[key]

    def _split(self, trees: dict[int, tuple]) -> TiledTable:
        new, names = self.tiles.split(trees)
        cut = sorted(trees)
        parts = sorted(n for t in cut for n in names[t])
        moved = self.rows.where(F.col("tile").isin(cut)).withColumn("tile", new.tile_of(F.col("x"), F.col("y")))
        old = np.array([t for t in range(self.tiles.n_tiles) for _ in names[t]])
        order = np.argsort([n for t in range(self.tiles.n_tiles) for n in names[t]])
        parent = old[order]
        measured, counts = measure(moved, new)
        whole = ~np.isin(np.arange(new.n_tiles), parts)
        mbr = np.where(whole[:, None], self.tiles.mbr[parent], measured.mbr)
        counts = np.where(whole, self.counts[parent], counts)
        number = by_tile([names[t][0] for t in range(self.tiles.n_tiles)], F.col("tile"), "int")
        stay = [part.where(~F.col("tile").isin(cut)).withColumn("tile", number) for part in self.parts]
        slots: list[int | None] | None = None
        if "slot" in self.df.columns:
            keys = slot_keys(self.df.sparkSession, self.n_slots)
            load = np.zeros(self.n_slots)
            slots = [self.slots[parent[t]] if whole[t] else None for t in range(new.n_tiles)]
            place = {k: i for i, k in enumerate(keys)}
            for t in np.flatnonzero(whole):
                load[place[slots[t]]] += counts[t]
            for t in sorted(parts, key=lambda t: -counts[t]):  # parts of one tile go to different slots, the heaviest to the lightest
                taken = {slots[u] for u in parts if parent[u] == parent[t]}
                i = min([i for i in range(self.n_slots) if keys[i] not in taken] or range(self.n_slots), key=lambda i: load[i])
                slots[t] = keys[i]
                load[i] += counts[t]
            moved = moved.withColumn("slot", by_tile(slots, F.col("tile"), "int")).repartition(self.n_slots, "slot").sortWithinPartitions("tile", "cell")
        if self.df.storageLevel.useMemory:  # what moved stands beside what is kept
            moved = moved.persist()
        store = None
        if self.filters is not None:  # a part asks its tile's filter, which knows the part's places too
            store = FilterStore({t: self.filters.filters[parent[t]] for t in range(new.n_tiles) if parent[t] in self.filters.filters}, self.filters.version)
        return TiledTable(stay[0], new.with_mbr(mbr), counts, self.n_slots, store, (*stay[1:], moved), None if slots is None else tuple(slots), tuple(len(stay) if not whole[t] else (self.lies_in[parent[t]] if self.more else 0) for t in range(new.n_tiles)))


def _by_identity(plan: planner.SplitPlan, handles):
    for h, _ in handles:
        if isinstance(h, planner.Histogram) and id(h) in plan.splits:
            yield h, plan.splits[id(h)]


def measure(tiled: DataFrame, tm: TileMap) -> tuple[TileMap, np.ndarray]:
    """Tight boxes and counts of all tiles: a row a tile comes to the driver."""
    mbr, counts = np.full((tm.n_tiles, 4), np.nan), np.zeros(tm.n_tiles, np.int64)
    rows = tiled.groupBy("tile").agg(F.min("x"), F.min("y"), F.max("x"), F.max("y"), F.count(F.lit(1))).collect()
    for t, *rest in rows:
        mbr[t], counts[t] = rest[:4], rest[4]
    return tm.with_mbr(mbr), counts
