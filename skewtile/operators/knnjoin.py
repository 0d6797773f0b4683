"""Nearest-neighbour joins: k candidates at home give a radius, the radius says which other tiles to ask, and the candidates are merged."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from skewtile.functions.geometry import dist2, maxdist2
from skewtile.operators import blocks, merge, rangejoin
from skewtile.operators import local as kernels
from skewtile.operators.tiled import FINEST, TiledTable
from skewtile.plans import route

_CANDIDATES = "qid long, pid long, x double, y double, dist2 double"
_LISTS = "pids array<long>, xs array<double>, ys array<double>, ds array<double>"
PIVOTS = 1024
"""Focal points of a sample whose own k-th distances bound all others."""


def _columns(data: DataFrame, routed: DataFrame, more: list[str]) -> tuple[list[str], DataFrame, DataFrame]:
    keys = [c for c in ("slot", "tile") if c in data.columns and c in routed.columns]
    data = data.select(*keys, F.col("pid").cast("long"), F.col("x").cast("double"), F.col("y").cast("double"))
    return keys, data, routed.select(*keys, F.col("qid").cast("long"), "cx", "cy", *more)


def _numpy(t: pa.Table, *names: str) -> list[np.ndarray]:
    return [t.column(c).to_numpy() for c in names]


def _search(algo: str, k: int, pid, x, y, cx, cy, r2=None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, point, squared distance) of the k first of each query, sorted by query and rank."""
    name = kernels.choose("point", len(x), len(cx), k) if algo == "auto" else algo
    qi, di, d = kernels.knn(name, pid, x, y, cx, cy, k, r2)
    order = np.lexsort((y[di], x[di], pid[di], d, qi))
    return qi[order], di[order], d[order]


def local_knn(data: DataFrame, routed: DataFrame, k: int, algo: str = "auto") -> DataFrame:
    """The k first of each tile for the focal points routed there."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        pid, x, y = _numpy(left, "pid", "x", "y")
        qid, cx, cy = _numpy(right, "qid", "cx", "cy")
        qi, di, d = _search(algo, k, pid, x, y, cx, cy)
        return pa.table([qid[qi], pid[di], x[di], y[di], d], ["qid", "pid", "x", "y", "dist2"])

    keys, data, routed = _columns(data, routed, [])
    return data.groupBy(*keys).cogroup(routed.groupBy(*keys)).applyInArrow(run, _CANDIDATES)


def bounded_knn(data: DataFrame, routed: DataFrame, k: int, algo: str, tt: TiledTable) -> DataFrame:
    """The same within squared radius r2. A tile is dealt out in parts of bounded size (see `blocks`), each of which gives its own k first: a
    task indexes a part's data and streams its focal points past them, and candidates leave in pieces."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pid, x, y, focal = blocks.first_side(batches, ("id", "x1", "y1"))
        ask = None
        for b in focal if len(pid) else ():
            qid, cx, cy, r2 = (b.column(c).to_numpy(zero_copy_only=False) for c in ("id", "x1", "y1", "r2"))
            if ask is None:
                ask = kernels.knn_probe(kernels.choose("point", len(x), len(cx), k) if algo == "auto" else algo, pid, x, y, k)
            for at, qi, di, d in ask(cx, cy, r2):
                if len(qi):
                    yield pa.RecordBatch.from_arrays([pa.array(v) for v in (qid[at][qi], pid[di], x[di], y[di], d)], ["qid", "pid", "x", "y", "dist2"])

    keys, data, routed = _columns(data, routed, ["r2"])
    slot = [c for c in keys if c == "slot"]
    data = data.select(*slot, "tile", F.col("pid").alias("id"), F.col("x").alias("x1"), F.col("y").alias("y1"))
    routed = routed.select(*slot, "tile", F.col("qid").alias("id"), F.col("cx").alias("x1"), F.col("cy").alias("y1"), "r2")
    return blocks.dealt(data, routed, tt.counts, slot, tt.n_slots).applyInArrow(run, _CANDIDATES)


def _home_round(data: DataFrame, homed: DataFrame, k: int, algo: str) -> DataFrame:
    """One row per focal point: its candidates at home as lists, and r2, the squared distance of candidate number `need`, if there is one."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        pid, x, y = _numpy(left, "pid", "x", "y")
        qid, cx, cy, need = _numpy(right, "qid", "cx", "cy", "need")
        qi, di, d = _search(algo, k, pid, x, y, cx, cy)
        at = np.append(0, np.cumsum(np.bincount(qi, minlength=len(qid)))).astype(np.int32)
        have = np.diff(at) >= need
        r2 = np.full(len(qid), np.nan)
        r2[have] = d[at[:-1][have] + need[have] - 1]
        lists = [pa.ListArray.from_arrays(pa.array(at), pa.array(v)) for v in (pid[di], x[di], y[di], d)]
        own = [right.column(c).combine_chunks() for c in ("qid", "cx", "cy", "need", "tile")]
        return pa.table([*own, pa.array(r2, mask=~have), *lists], ["qid", "cx", "cy", "need", "home", "known", "pids", "xs", "ys", "ds"])

    keys, data, homed = _columns(data, homed, ["need"])
    out = f"qid long, cx double, cy double, need int, home int, known double, {_LISTS}"
    return data.groupBy(*keys).cogroup(homed.groupBy(*keys)).applyInArrow(run, out)


def _away_round(data: DataFrame, routed: DataFrame, k: int, algo: str) -> DataFrame:
    """The candidates within the radius of the focal points sent to other tiles, and the candidates from home as they are."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        pid, x, y = _numpy(left, "pid", "x", "y")
        qid, cx, cy, r2, carries = _numpy(right, "qid", "cx", "cy", "r2", "carries")
        ask = ~carries.astype(bool)
        qi, di, d = _search(algo, k, pid, x, y, cx[ask], cy[ask], r2[ask])
        lists = [right.column(c).combine_chunks().filter(pa.array(~ask)) for c in ("pids", "xs", "ys", "ds")]
        held = np.repeat(qid[~ask], lists[0].value_lengths().to_numpy(zero_copy_only=False)) if (~ask).any() else qid[:0]
        pids, xs, ys, ds = (v.flatten().to_numpy(zero_copy_only=False) for v in lists)
        parts = (qid[ask][qi], held), (pid[di], pids), (x[di], xs), (y[di], ys), (d, ds)
        return pa.table([np.concatenate(p) for p in parts], ["qid", "pid", "x", "y", "dist2"])

    keys, data, routed = _columns(data, routed, ["r2", "carries", "pids", "xs", "ys", "ds"])
    return data.groupBy(*keys).cogroup(routed.groupBy(*keys)).applyInArrow(run, _CANDIDATES)


def catalyst_knn(tt: TiledTable, routed: DataFrame) -> DataFrame:
    """The same as one equi-join on cells and a residual radius (column r2), the k first a query left to the merge: no Python."""
    r, (fx1, fy1, fx2, fy2) = F.sqrt("r2") * (1 + 1e-12), tt.frame
    routed = routed.withColumns({
        "x1": F.greatest(F.col("cx") - r, F.lit(fx1)), "y1": F.greatest(F.col("cy") - r, F.lit(fy1)), "x2": F.least(F.col("cx") + r, F.lit(fx2)), "y2": F.least(F.col("cy") + r, F.lit(fy2)),
    })
    cells = rangejoin.Cells.of(routed, tt.tiles)
    near = merge.union([rangejoin.cell_join(part.select("pid", "x", "y", *tt.keys), tt.of_part(routed, i), cells, tt.tiles).select("qid", "pid", "x", "y", "cx", "cy", "r2") for i, part in enumerate(tt.parts)])
    return near.withColumn("dist2", dist2(F.col("x"), F.col("y"), F.col("cx"), F.col("cy"))).where("dist2 <= r2").select("qid", "pid", "x", "y", "dist2")


def cell_bound(q: DataFrame, tt: TiledTable, enough: Column) -> DataFrame:
    """q with cell_r2: the farthest corner of the data of the best cell around the focal point that holds enough points; null if none does."""
    gx, gy = tt.fine(F.col("cx"), F.col("cy"))
    f = q.select("qid", "cx", "cy", enough.alias("_enough"), gx.alias("_gx"), gy.alias("_gy"), F.explode(F.sequence(F.lit(1), F.lit(FINEST))).alias("level"))
    up = lambda c: F.call_function("shiftright", F.col(c), 2 * (FINEST - F.col("level")))
    f = f.withColumns({"gx": up("_gx"), "gy": up("_gy")}).drop("_gx", "_gy")
    held = f.join(tt.cell_counts(), ["level", "gx", "gy"]).where("n >= _enough")
    best = held.groupBy("qid").agg(F.min(maxdist2(F.col("cx"), F.col("cy"), F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"))).alias("cell_r2"))
    return q.join(best, "qid", "left")


def replanned(q: DataFrame, tt: TiledTable, budget: int, by: str = "query") -> TiledTable:
    """The table with the tiles cut that receive too many focal points; only their rows move."""
    at = route.home(q, tt.tiles).select("tile", F.col("cx").alias("x1"), F.col("cy").alias("y1"), F.col("cx").alias("x2"), F.col("cy").alias("y2"))
    return tt.apply(tt.plan(at, budget, by))


def knn_join(
    q: DataFrame, tt: TiledTable, k: int | Column = 10, bound: str = "home", local: str = "auto", filter: bool = False, plan: str | None = None,
    budget: int = 8, exclude_self: bool = False, sample: int = PIVOTS, most: int | None = None,
) -> DataFrame:
    """(qid, pid, dist2, rank): exactly the k nearest points of each focal point (qid, cx, cy), ties by pid, x, y.

    bound: where the radius comes from. "home": the k-th candidate in the own tile, else the tiles' boxes and counts; the candidates
    go on with their focal point, so neither round is run twice. "sample": the k-th distances of sampled focal points, with one round for
    all others. "counts": boxes and counts alone, those of tiles and of cells. k may be a column of q; `most` is then its largest value. exclude_self leaves out
    pid = qid. Where the data lie by slot, both rounds leave them there."""
    per_query = isinstance(k, Column)
    top = most if per_query else k
    if per_query and most is None:
        raise ValueError("a column k needs its largest value, most")
    want = k if per_query else F.lit(int(k))
    q = q.select("qid", F.col("cx").cast("double"), F.col("cy").cast("double"), want.cast("int").alias("k")).where("k > 0")
    need = (top or 0) + (1 if exclude_self else 0)
    if plan:
        tt = replanned(q, tt, budget, plan)
    if filter and tt.filters is None:
        tt = tt.with_filters()
    store = tt.filters if filter else None
    enough = F.col("k") + int(exclude_self)
    if bound == "home":
        found = _by_home(q.withColumn("need", enough.cast("int")), tt, need, local, store)
    else:
        counts = route.bound_from_counts(F.col("cx"), F.col("cy"), tt.tiles, tt.counts, enough)
        if local == "catalyst" or bound == "counts":
            q = cell_bound(q, tt, enough)
            counts = F.least(counts, F.coalesce("cell_r2", F.lit(float("inf"))))
        r2 = counts if bound == "counts" else F.least(counts, _sample_bound(q, tt, need, sample))
        routed = tt.place(route.circles(q, tt.tiles, r2, store))
        if local == "catalyst":
            found = catalyst_knn(tt, routed)
        else:
            found = merge.union([bounded_knn(part, tt.of_part(routed, i), need, local, tt) for i, part in enumerate(tt.parts)])
    return _merged(q, found, k if not per_query else None, exclude_self)


def _by_home(q: DataFrame, tt: TiledTable, k: int, local: str, store) -> DataFrame:
    homed = tt.place(route.home(q, tt.tiles))
    asked = [tt.of_part(homed, i) for i in range(len(tt.parts))]
    first = merge.union([_home_round(tt.visited(part, own), own, k, local) for part, own in zip(tt.parts, asked)])
    r2 = route.bound_from_counts(F.col("cx"), F.col("cy"), tt.tiles, tt.counts, F.col("need"), F.col("known"))
    met = first.withColumn("r2", r2)
    reach = F.sqrt("r2") * (1 + 1e-12)
    tiles = tt.tiles.tiles_meeting(F.col("cx") - reach, F.col("cy") - reach, F.col("cx") + reach, F.col("cy") + reach)
    sent = met.withColumn("tile", F.explode(F.concat(F.array("home"), F.filter(tiles, lambda t: t != F.col("home"))))).withColumn("carries", F.col("tile") == F.col("home"))
    for c in ("pids", "xs", "ys", "ds"):
        sent = sent.withColumn(c, F.when(F.col("carries"), F.col(c)))
    sent = sent.where(F.col("carries") | route.meets_disc(tt.tiles))
    sent = tt.place(route.prune_discs(sent, store, F.col("carries")))
    return merge.union([_away_round(part, tt.of_part(sent, i), k, local) for i, part in enumerate(tt.parts)])


def _merged(q: DataFrame, found: DataFrame, k: int | None, exclude_self: bool) -> DataFrame:
    if exclude_self:
        found = found.where("qid <> pid")
    if k is not None:
        return merge.topk(found, k)
    return merge.topk(found.join(q.select("qid", "k"), "qid"), F.col("k"))


def _sample_bound(q: DataFrame, tt: TiledTable, k: int, sample: int) -> Column:
    """A squared radius from a bounded sample of the focal points: a point's distance to a sampled one plus that one's own k-th distance holds k
    points for sure; the least over the sample is taken."""
    some = q.orderBy(F.xxhash64("qid"), "cx", "cy").limit(max(1, sample))
    some = some.select(F.monotonically_increasing_id().alias("qid"), "cx", "cy")
    pivots = some.toPandas()  # `sample` rows
    some = tt.df.sparkSession.createDataFrame(pivots, "qid long, cx double, cy double")
    kth = {r["qid"]: r["d"] for r in knn_join(some, tt, k).where(F.col("rank") == k).select("qid", F.col("dist2").alias("d")).collect()}  # `sample` rows
    at = pivots[pivots["qid"].isin(list(kth))]
    if not len(at):
        return F.lit(float("inf"))
    px, py, reach = at["cx"].to_numpy(), at["cy"].to_numpy(), np.sqrt([kth[i] for i in at["qid"]])

    @F.pandas_udf("double")
    def bound(cx: pd.Series, cy: pd.Series) -> pd.Series:
        out = np.empty(len(cx))
        step = max(1, (1 << 20) // len(px))
        for a in range(0, len(cx), step):
            x, y = cx.to_numpy()[a : a + step, None], cy.to_numpy()[a : a + step, None]
            out[a : a + step] = (np.hypot(x - px, y - py) + reach).min(1)
        return pd.Series((out * (1 + 1e-12)) ** 2 + 1e-9)

    return bound(F.col("cx"), F.col("cy"))


def self_knn_join(points: DataFrame, tt: TiledTable, k: int, exclude_self: bool = True, **options) -> DataFrame:
    return knn_join(points.select(F.col("pid").alias("qid"), F.col("x").alias("cx"), F.col("y").alias("cy")), tt, k, exclude_self=exclude_self, **options)


def empty_discs(q: DataFrame, tt: TiledTable) -> DataFrame:
    """(tile, x1, y1, x2, y2): what a nearest-neighbour join found to be empty. Nothing lies nearer to a focal point than its nearest point, so
    the square within that circle is empty in every tile that it meets."""
    nearest = knn_join(q, tt, 1).select("qid", F.sqrt("dist2").alias("_d"))
    inner = q.select("qid", "cx", "cy").join(nearest, "qid").withColumn("_h", F.col("_d") * (0.5**0.5) * (1 - 1e-9)).where("_h > 0")
    w = inner.select("qid", (F.col("cx") - F.col("_h")).alias("x1"), (F.col("cy") - F.col("_h")).alias("y1"), (F.col("cx") + F.col("_h")).alias("x2"), (F.col("cy") + F.col("_h")).alias("y2"))
    return route.ranges(w, tt.tiles, tt.filters).select("tile", "x1", "y1", "x2", "y2")


def adapt(q: DataFrame, tt: TiledTable, border: str = "exact", max_depth: int = 9, max_bits: int | None = None) -> TiledTable:
    """One round of learning from a batch of nearest-neighbour queries."""
    tt = tt if tt.filters is not None else tt.with_filters()
    return tt.like(filters=tt.filters.refresh(tt.rows, empty_discs(q, tt), border, max_depth, max_bits))
