"""The methods, variants, baselines, measures and experiment workloads as queries over the given tables, with their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from skewtile import metrics
from skewtile.operators import baselines as bl
from skewtile.operators import knnjoin, rangejoin, search, shapes
from skewtile.operators.tiled import TiledTable
from skewtile.plans import planner, route
from skewtile.plans.cost import CostModel, Tile
from skewtile.plans.tilemap import TileMap, by_key_mod
from skewtile.sources import planes as pl
from skewtile.sources.formats import scratch

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
TILES = 16


def query(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


def tiled(spark: SparkSession, sf: str, plane: str = "E", part: tuple[int, int] | None = None, **options) -> TiledTable:
    """A plane as a tiled table; part (i, m): only pid % m < i."""
    points = pl.PLANES[plane](spark, sf)
    if part:
        points = points.where(F.col("pid") % part[1] < part[0])
    return TiledTable.build(points, TILES, **options)


E, L, O = pl.SQL["E"], pl.SQL["L"], pl.SQL["O"]  # noqa: E741
_IN = "d.x BETWEEN q.x1 AND q.x2 AND d.y BETWEEN q.y1 AND q.y2"


def _theta(windows: str, data: str, where: str = "") -> str:
    return f"SELECT q.qid, d.pid FROM {windows} q JOIN {data} d ON {_IN}{where}"


# range searches ---------------------------------------------------------------------------------

_WINDOWS = {"range_search_events": ("E", (500000, 0, 800000, 200000), "kd"), "range_search_events_2": ("E", (1000000, 100000, 1500000, 600000), "quadtree"), "range_search_events_3": ("E", (0, 2200000, 3000000, 3000000), "str"), "range_search_lineitem": ("L", (2000000, 4000000, 3000000, 5000000), "quadtree")}
for _name, (_plane, _box, _kind) in _WINDOWS.items():
    query(
        _name,
        lambda s, d, p=_plane, b=_box, k=_kind: search.range_search(tiled(s, d, p, kind=k), tuple(map(float, b))).select("pid", "x", "y"),
        f"SELECT pid, x, y FROM {pl.SQL[_plane]} WHERE x BETWEEN {_box[0]} AND {_box[2]} AND y BETWEEN {_box[1]} AND {_box[3]}",
    )
query(
    "range_search_circle_events",
    lambda s, d: search.range_search(tiled(s, d, with_filters=True), (700000.0, 100000.0, 100000.0)).select("pid", "x", "y"),
    f"SELECT pid, x, y FROM {E} WHERE (x - 700000) * (x - 700000) + (y - 100000) * (y - 100000) <= 1e10",
)
_RING = ((600000.0, 0.0), (900000.0, 50000.0), (800000.0, 300000.0), (700000.0, 120000.0))


def _ring_sql(ring) -> str:
    odd = " + ".join(f"CAST((({a[1]:.0f} > y) <> ({b[1]:.0f} > y)) AND x < ({b[0] - a[0]:.0f}e0) * (y - {a[1]:.0f}) / ({b[1] - a[1]:.0f}e0) + {a[0]:.0f} AS INTEGER)" for a, b in zip(ring, [*ring[1:], ring[0]]))
    edge = " OR ".join(f"(({b[0] - a[0]:.0f}) * (y - {a[1]:.0f}) - ({b[1] - a[1]:.0f}) * (x - {a[0]:.0f}) = 0 AND x BETWEEN {min(a[0], b[0]):.0f} AND {max(a[0], b[0]):.0f} AND y BETWEEN {min(a[1], b[1]):.0f} AND {max(a[1], b[1]):.0f})" for a, b in zip(ring, [*ring[1:], ring[0]]))
    return f"(({odd}) % 2 = 1 OR {edge})"


query("range_search_polygon", lambda s, d: search.polygon_search(tiled(s, d), _RING).select("pid", "x", "y"), f"SELECT pid, x, y FROM {E} WHERE {_ring_sql(_RING)}")


def _keyword(s: SparkSession, d: str) -> DataFrame:
    docs = pl.table(s, d, "documents")
    n = docs.count()
    points = pl.events(s, d).withColumn("doc_id", F.col("pid") % n)
    near = search.range_search(TiledTable.build(points, TILES), (500000.0, 0.0, 800000.0, 200000.0), keyword="the", texts=docs.select("doc_id", "text"))
    return near.select("pid")


query("range_search_keyword", _keyword, f"SELECT e.pid FROM {E} e JOIN documents t ON t.doc_id = e.pid % (SELECT count(*) FROM documents) WHERE x BETWEEN 500000 AND 800000 AND y BETWEEN 0 AND 200000 AND list_contains(regexp_split_to_array(lower(t.text), '[^a-z0-9]+'), 'the')")

# range joins ------------------------------------------------------------------------------------


def _area(spark: SparkSession, sf: str, area: str | None, **options) -> DataFrame:
    every = 5 if area else 50
    return rangejoin.range_join(pl.windows_of(pl.events(spark, sf), 20000.0, every, area), tiled(spark, sf), **options)


def _area_sql(area: str | None) -> str:
    return _theta(pl.windows_sql("E", 20000, 5 if area else 50, area), E)


for _a in ("a", "b", "c"):
    query(f"range_join_area_{_a}", lambda s, d, a=_a: _area(s, d, a), _area_sql(_a))
    query(f"range_join_area_{_a}_opt", lambda s, d, a=_a: _area(s, d, a, plan="query", filter=True), _area_sql(_a))
query("range_join_area_all", lambda s, d: _area(s, d, None), _area_sql(None))
query("range_join_area_all_opt", lambda s, d: _area(s, d, None, plan="query", filter=True), _area_sql(None))
query("range_join_lineitem", lambda s, d: rangejoin.range_join(pl.windows_of(pl.lineitem(s, d), 100000.0, 199), tiled(s, d, "L")), _theta(pl.windows_sql("L", 100000, 199), L))


def _orders_lineitem(s: SparkSession, d: str) -> DataFrame:
    q = pl.orders(s, d).withColumns({"x": F.col("x") / 5, "y": F.col("y") / 5})
    return rangejoin.range_join(pl.windows_of(q, 100000.0, 50), tiled(s, d, "L"))


query("range_join_orders_lineitem", _orders_lineitem, _theta(pl.windows_sql("O", 100000, 50, scale=" / 5"), L))
_VARIANTS = {
    "noopt": {}, "filter": {"filter": True}, "plan_query": {"plan": "query"}, "plan_data": {"plan": "data"}, "plan_product": {"plan": "product"}, "binary": {"plan": "query", "mode": "binary"}, "best": {"plan": "query", "mode": "best"},
    "dedup": {"dedup": True}, "replicate_inner": {"strategy": "replicate_inner"},
    "local_rtree": {"local": "inl_rtree"}, "local_grid": {"local": "inl_grid"}, "local_quadtree": {"local": "inl_quadtree"}, "local_dual": {"local": "dual_tree"}, "local_brute": {"local": "brute"}, "local_auto": {"local": "auto"},
}
_VARIANTS |= {"plan_sampled": {"plan": "sampled"}, "plan_calibrated": {"plan": "calibrated"}}
for _n, _o in _VARIANTS.items():
    query(f"range_join_{_n}", lambda s, d, o=_o: _area(s, d, "a", **o), _area_sql("a"))
for _k in ("str", "quadtree", "grid"):
    query(f"range_join_tiles_{_k}", lambda s, d, k=_k: rangejoin.range_join(pl.windows_of(pl.events(s, d), 20000.0, 5, "a"), tiled(s, d, kind=k), filter=True), _area_sql("a"))
query("range_join_aqe", lambda s, d: rangejoin.aqe_join(pl.windows_of(pl.events(s, d), 20000.0, 5, "a"), tiled(s, d)), _area_sql("a"))
query("range_join_salted", lambda s, d: rangejoin.salted_join(pl.windows_of(pl.events(s, d), 20000.0, 5, "a"), tiled(s, d)), _area_sql("a"))
for _h, _tail in (("left", "SELECT q.qid, d.pid FROM {w} q LEFT JOIN {e} d ON {c}"), ("semi", "SELECT q.qid FROM {w} q WHERE EXISTS (SELECT 1 FROM {e} d WHERE {c})"), ("anti", "SELECT q.qid FROM {w} q WHERE NOT EXISTS (SELECT 1 FROM {e} d WHERE {c})")):
    _w = f"(SELECT qid, x1 + 30000 AS x1, y1 + 300000 AS y1, x2 + 30000 AS x2, y2 + 300000 AS y2 FROM {pl.windows_sql('E', 10000, 10)})"

    def _shifted(s, d, h=_h):
        w = pl.windows_of(pl.events(s, d), 10000.0, 10)
        w = w.select("qid", (F.col("x1") + 30000).alias("x1"), (F.col("y1") + 300000).alias("y1"), (F.col("x2") + 30000).alias("x2"), (F.col("y2") + 300000).alias("y2"))
        return rangejoin.range_join(w, tiled(s, d), filter=True, how=h)

    query(f"range_join_{_h}", _shifted, _tail.format(w=_w, e=E, c=_IN))
query("range_join_self", lambda s, d: rangejoin.self_range_join(by_key_mod(pl.events(s, d), 5), tiled(s, d), 10000.0), _theta(pl.windows_sql("E", 10000, 5), E, " AND q.qid <> d.pid"))
for _i in range(1, 7):
    query(
        f"range_join_size_{_i}",
        lambda s, d, i=_i: rangejoin.range_join(pl.windows_of(pl.events(s, d), 20000.0, 50), tiled(s, d, part=(i, 6))).agg(F.count(F.lit(1)).alias("n_pairs")),
        f"SELECT count(*) AS n_pairs FROM {pl.windows_sql('E', 20000, 50)} q JOIN {E} d ON {_IN} WHERE d.pid % 6 < {_i}",
    )
for _m in (400, 200, 100, 40):
    query(
        f"range_join_q_{_m}",
        lambda s, d, m=_m: rangejoin.range_join(pl.windows_of(pl.events(s, d), 20000.0, m), tiled(s, d)).agg(F.count(F.lit(1)).alias("n_pairs")),
        f"SELECT count(*) AS n_pairs FROM {pl.windows_sql('E', 20000, _m)} q JOIN {E} d ON {_IN}",
    )


def _disc_sql(r: str) -> str:
    return f"SELECT q.pid AS qid, d.pid FROM {E} q JOIN {E} d ON (d.x - q.x) * (d.x - q.x) + (d.y - q.y) * (d.y - q.y) <= {r} * {r} WHERE q.pid % 40 = 0"


for _r in (20000, 50000):
    query(f"distance_join_r{_r}", lambda s, d, r=_r: rangejoin.distance_join(pl.focal_points(pl.events(s, d), 40), tiled(s, d), float(r)), _disc_sql(f"{_r}e0"))
query("distance_join_opt", lambda s, d: rangejoin.distance_join(pl.focal_points(pl.events(s, d), 40), tiled(s, d), 20000.0, plan="query", filter=True), _disc_sql("20000e0"))
query(
    "distance_join_own_radius",
    lambda s, d: rangejoin.distance_join(pl.focal_points(pl.events(s, d), 40).withColumn("r", (F.col("qid") % 7 + 1) * 5000.0), tiled(s, d)),
    _disc_sql("((q.pid % 7 + 1) * 5000e0)"),
)

# nearest neighbours -----------------------------------------------------------------------------


def _knn_search_sql(k: int, where: str = "TRUE") -> str:
    d2 = "(x - 700000) * (x - 700000) + (y - 100000) * (y - 100000)"
    return f"SELECT pid, x, y, {d2} AS dist2, row_number() OVER (ORDER BY {d2}, pid, x, y) AS rank FROM {E} WHERE {where} QUALIFY rank <= {k}"


for _k in (10, 20, 30):
    query(f"knn_search_k{_k}", lambda s, d, k=_k: search.knn_search(tiled(s, d, with_filters=True), 700000.0, 100000.0, k), _knn_search_sql(_k))
query(
    "knn_search_where",
    lambda s, d: search.knn_search(TiledTable.build(pl.events(s, d, "event_type"), TILES), 700000.0, 100000.0, 10, F.col("event_type") == "click"),
    _knn_search_sql(10, "event_type = 'click'"),
)


def _knn_sql(k: str, focal: str = f"(SELECT pid AS qid, x AS cx, y AS cy, pid % 5 + 1 AS k FROM {E} WHERE pid % 40 = 0)", data: str = E, where: str = "TRUE") -> str:
    return (
        f"SELECT qid, pid, dist2, rank FROM (SELECT qid, pid, dist2, k, row_number() OVER (PARTITION BY qid ORDER BY dist2, pid, x, y) AS rank FROM "
        f"(SELECT q.qid, q.k, d.pid, d.x, d.y, (d.x - q.cx) * (d.x - q.cx) + (d.y - q.cy) * (d.y - q.cy) AS dist2 FROM {focal} q CROSS JOIN {data} d WHERE {where})) WHERE rank <= {k}"
    )


def _knn(spark: SparkSession, sf: str, k: int = 10, **options) -> DataFrame:
    return knnjoin.knn_join(pl.focal_points(pl.events(spark, sf), 40), tiled(spark, sf), k, **options)


for _k in (10, 50, 100, 150):
    query(f"knn_join_k{_k}_events", lambda s, d, k=_k: _knn(s, d, k, filter=True), _knn_sql(str(_k)))
for _n, _o in {"noopt": {}, "opt": {"plan": "query", "filter": True}, "sample_bound": {"bound": "sample"}, "count_bound": {"bound": "counts"}, "catalyst": {"bound": "counts", "local": "catalyst"}}.items():
    query(f"knn_join_{_n}", lambda s, d, o=_o: _knn(s, d, **o), _knn_sql("10"))
for _n, _algo in {"quadtree": "inl_quadtree", "rtree": "inl_rtree", "grid": "inl_grid", "hilbert": "hilbert_block", "pivot": "pivot_block", "halo": "halo_self", "pca": "pca_block"}.items():
    query(f"knn_join_local_{_n}", lambda s, d, a=_algo: _knn(s, d, local=a), _knn_sql("10"))
query("knn_join_own_k", lambda s, d: knnjoin.knn_join(pl.focal_points(pl.events(s, d), 40).withColumn("k", F.col("qid") % 5 + 1), tiled(s, d), F.col("k"), most=5), _knn_sql("k"))


def _own(s: SparkSession, d: str) -> DataFrame:
    points = pl.embeddings(s, d)
    return knnjoin.self_knn_join(points, TiledTable.build(points, 8), 5)


query("knn_join_self", _own, _knn_sql("5", f"(SELECT pid AS qid, x AS cx, y AS cy, 5 AS k FROM {pl.SQL['V']})", pl.SQL["V"], "q.qid <> d.pid"))
_HOT = f"(SELECT pid AS qid, x AS cx, y AS cy, 10 AS k FROM {E} WHERE pid % 5 = 0 AND x BETWEEN 600000 AND 900000 AND y BETWEEN 0 AND 300000)"


def _hot(s: SparkSession, d: str, i: int, **options) -> DataFrame:
    x1, y1, x2, y2 = pl.AREAS["a"]
    points = pl.events(s, d)
    q = pl.focal_points(points.where(F.col("x").between(x1, x2) & F.col("y").between(y1, y2)), 5)
    return knnjoin.knn_join(q, tiled(s, d, part=(i, 4)), 10, **options)


for _i in range(1, 5):
    query(f"knn_join_hot_frac_{_i}", lambda s, d, i=_i: _hot(s, d, i, plan="query", filter=True), _knn_sql("10", _HOT, f"(SELECT * FROM {E} WHERE pid % 4 < {_i})"))

# the second plane: the same workloads on line items ---------------------------------------------

_L_DISC = "(x - 2500000) * (x - 2500000) + (y - 4500000) * (y - 4500000)"
for _k in (10, 20, 30):
    query(
        f"knn_search_k{_k}_lineitem",
        lambda s, d, k=_k: search.knn_search(tiled(s, d, "L", with_filters=True), 2500000.0, 4500000.0, k),
        f"SELECT pid, x, y, {_L_DISC} AS dist2, row_number() OVER (ORDER BY {_L_DISC}, pid, x, y) AS rank FROM {L} QUALIFY rank <= {_k}",
    )
for _i, _box in enumerate(((0, 0, 1500000, 3000000), (4000000, 6000000, 6000000, 9000000)), 2):
    query(
        f"range_search_lineitem_{_i}",
        lambda s, d, b=_box: search.range_search(tiled(s, d, "L", kind="str"), tuple(map(float, b))).select("pid", "x", "y"),
        f"SELECT pid, x, y FROM {L} WHERE x BETWEEN {_box[0]} AND {_box[2]} AND y BETWEEN {_box[1]} AND {_box[3]}",
    )
_L_FOCAL = f"(SELECT pid AS qid, x AS cx, y AS cy FROM {L} WHERE l_orderkey % 400 = 0)"
_l_focal = lambda s, d: pl.lineitem(s, d, "l_orderkey").where("l_orderkey % 400 = 0").select(F.col("pid").alias("qid"), F.col("x").alias("cx"), F.col("y").alias("cy"))


def _l_knn_sql(k: int, focal: str = _L_FOCAL, where: str = "TRUE") -> str:
    return _knn_sql(str(k), f"(SELECT *, {k} AS k FROM {focal})", L, where)


for _k in (50, 100, 150):
    for _n, _o in (("", {}), ("_opt", {"plan": "query", "filter": True})):
        query(f"knn_join_k{_k}_lineitem{_n}", lambda s, d, k=_k, o=_o: knnjoin.knn_join(_l_focal(s, d), tiled(s, d, "L"), k, **o), _l_knn_sql(_k))
_L_W = "(SELECT pid AS qid, x - 60000 AS x1, y - 60000 AS y1, x + 60000 AS x2, y + 60000 AS y2 FROM {l} WHERE {w})"


def _l_windows(s: SparkSession, d: str, where: str) -> DataFrame:
    p = pl.lineitem(s, d, "l_orderkey").where(where)
    return p.select(F.col("pid").alias("qid"), (F.col("x") - 60000).alias("x1"), (F.col("y") - 60000).alias("y1"), (F.col("x") + 60000).alias("x2"), (F.col("y") + 60000).alias("y2"))


_COUNT = "SELECT count(*) AS n_pairs FROM {w} q JOIN {l} d ON {c} WHERE {p}"
for _i in range(1, 7):
    query(
        f"range_join_lineitem_size_{_i}",
        lambda s, d, i=_i: rangejoin.range_join(_l_windows(s, d, "l_orderkey % 400 = 0"), TiledTable.build(pl.lineitem(s, d, "l_orderkey").where(F.col("l_orderkey") % 6 < i), TILES)).agg(F.count(F.lit(1)).alias("n_pairs")),
        _COUNT.format(w=_L_W.format(l=L, w="l_orderkey % 400 = 0"), l=L, c=_IN, p=f"d.l_orderkey % 6 < {_i}"),
    )
for _m in (1600, 800, 400, 200):
    query(
        f"range_join_lineitem_q_{_m}",
        lambda s, d, m=_m: rangejoin.range_join(_l_windows(s, d, f"l_orderkey % {m} = 0"), tiled(s, d, "L")).agg(F.count(F.lit(1)).alias("n_pairs")),
        _COUNT.format(w=_L_W.format(l=L, w=f"l_orderkey % {_m} = 0"), l=L, c=_IN, p="TRUE"),
    )
_L_AREAS = {"a": (1000000, 2000000, 1800000, 2800000), "b": (3000000, 5000000, 3600000, 5600000), "c": (5000000, 1000000, 7000000, 3000000)}
for _a, _b in _L_AREAS.items():
    _in = f"l_orderkey % 20 = 0 AND x BETWEEN {_b[0]} AND {_b[2]} AND y BETWEEN {_b[1]} AND {_b[3]}"
    for _n, _o in (("", {}), ("_opt", {"plan": "query", "filter": True})):
        query(f"range_join_lineitem_area_{_a}{_n}", lambda s, d, w=_in, o=_o: rangejoin.range_join(_l_windows(s, d, w), tiled(s, d, "L"), **o), _theta(_L_W.format(l=L, w=_in), L))
_in = f"l_orderkey % 40 = 0 AND x BETWEEN {_L_AREAS['a'][0]} AND {_L_AREAS['a'][2]} AND y BETWEEN {_L_AREAS['a'][1]} AND {_L_AREAS['a'][3]}"


def _l_hot(s: SparkSession, d: str, i: int, where: str) -> DataFrame:
    q = pl.lineitem(s, d, "l_orderkey").where(where).select(F.col("pid").alias("qid"), F.col("x").alias("cx"), F.col("y").alias("cy"))
    data = pl.lineitem(s, d, "l_orderkey").where(F.col("l_orderkey") % 4 < i)
    return knnjoin.knn_join(q, TiledTable.build(data, TILES), 10, plan="query", filter=True)


for _i in range(1, 5):
    query(
        f"knn_join_lineitem_hot_frac_{_i}",
        lambda s, d, i=_i, w=_in: _l_hot(s, d, i, w),
        _l_knn_sql(10, f"(SELECT pid AS qid, x AS cx, y AS cy FROM {L} WHERE {_in})", f"d.l_orderkey % 4 < {_i}"),
    )

# edge cases that integers and small k hide ------------------------------------------------------

_TENTHS = f"(SELECT pid, x / 10 AS x, y / 10 AS y FROM {E})"


def _tenths(s: SparkSession, d: str) -> DataFrame:
    return pl.events(s, d).withColumns({"x": F.col("x") / 10, "y": F.col("y") / 10})


query(
    "distance_join_fractional",
    lambda s, d: rangejoin.distance_join(pl.focal_points(_tenths(s, d), 40), TiledTable.build(_tenths(s, d), TILES), 2000.3),
    f"SELECT q.pid AS qid, d.pid FROM {_TENTHS} q JOIN {_TENTHS} d ON (d.x - q.x) * (d.x - q.x) + (d.y - q.y) * (d.y - q.y) <= 2000.3e0 * 2000.3e0 WHERE q.pid % 40 = 0",
)
query(
    "distance_join_kernel",
    lambda s, d: rangejoin.distance_join(pl.focal_points(_tenths(s, d), 40), TiledTable.build(_tenths(s, d), TILES), 2000.3, local="auto"),
    f"SELECT q.pid AS qid, d.pid FROM {_TENTHS} q JOIN {_TENTHS} d ON (d.x - q.x) * (d.x - q.x) + (d.y - q.y) * (d.y - q.y) <= 2000.3e0 * 2000.3e0 WHERE q.pid % 40 = 0",
)
for _n in ("home", "counts", "sample"):
    query(
        "knn_join_k_beyond_rows" + ("" if _n == "home" else f"_{_n}"),
        lambda s, d, b=_n: knnjoin.knn_join(pl.focal_points(pl.customers(s, d), 30), TiledTable.build(pl.customers(s, d), 4, with_filters=True), 2000, bound=b, filter=True),
        _knn_sql("2000", f"(SELECT pid AS qid, x AS cx, y AS cy, 2000 AS k FROM {pl.SQL['C']} WHERE pid % 30 = 0)", pl.SQL["C"]),
    )

# baselines --------------------------------------------------------------------------------------

_w = lambda s, d: pl.windows_of(pl.events(s, d), 20000.0, 5, "a")
_f = lambda s, d: pl.focal_points(pl.events(s, d), 40)
query("baseline_allparts_range", lambda s, d: bl.allparts_range(_w(s, d), tiled(s, d)), _area_sql("a"))
query("baseline_allparts_knn", lambda s, d: bl.allparts_knn(_f(s, d), tiled(s, d), 10), _knn_sql("10"))
query("baseline_tilescan_range", lambda s, d: bl.tilescan_range(_w(s, d), tiled(s, d)), _area_sql("a"))
query("baseline_tilescan_disk_range", lambda s, d: bl.tilescan_range(_w(s, d), tiled(s, d), "disk_index", scratch(s, "tiles")), _area_sql("a"))
query("baseline_cartesian_range", lambda s, d: bl.cartesian_range(_w(s, d), pl.events(s, d)), _area_sql("a"))
query("baseline_cartesian_knn", lambda s, d: bl.cartesian_knn(_f(s, d), pl.events(s, d), 10), _knn_sql("10"))
query("baseline_pivot_knn", lambda s, d: bl.pivot_knn(_f(s, d), pl.events(s, d), 10, stage=scratch(s, "pivots")), _knn_sql("10"))
_SQUARE = f"SELECT q.pid AS qid, d.pid FROM {E} q JOIN {E} d ON d.x BETWEEN q.x - 20000 AND q.x + 20000 AND d.y BETWEEN q.y - 20000 AND q.y + 20000 WHERE q.pid % 40 = 0"
for _n, _opt in (("", False), ("_opt", True)):
    query(f"baseline_datarep_distance{_n}", lambda s, d, o=_opt: bl.datarep_distance_join(_f(s, d), tiled(s, d), 20000.0, o), _SQUARE)
    query(f"baseline_datarep_knn{_n}", lambda s, d, o=_opt: bl.datarep_knn(_f(s, d), tiled(s, d), 10, o), _knn_sql("10"))


def _bloom(s: SparkSession, d: str) -> DataFrame:
    """Points must all be found; the share of shifted points that are is the filter's false-positive rate."""
    points = pl.events(s, d)
    out = bl.bloom_rows(points, points.select(F.col("pid").alias("qid"), F.col("x").alias("cx"), F.col("y").alias("cy")))
    return out.agg(F.count_if("maybe").alias("found"), F.count_if(~F.col("maybe")).alias("missed"))


query("baseline_bloom", _bloom, "SELECT count(*) AS found, 0 AS missed FROM events")


def _probe(s: SparkSession, d: str) -> DataFrame:
    """Each structure on each tile of all events, built and probed in that tile's task; sums of the build times and sizes, means of the rest."""
    kinds = ("rtree", "quadtree", "obf", "obf_adaptive", "bloom")

    def run(pdf):
        x, y = pdf["x"].to_numpy(float), pdf["y"].to_numpy(float)
        rng = np.random.default_rng(int(pdf["tile"].iloc[0]))
        low, wide = np.array([x.min(), y.min()]), np.array([np.ptp(x), np.ptp(y)])
        corner = low + rng.random((100, 2)) * wide
        probes = np.column_stack([corner, corner + np.maximum(wide / 40, 1.0)])
        return pd.DataFrame([(k, *(float(v) for v in bl.index_probe(k, x, y, probes).values())) for k in kinds], columns=["kind", "build_s", "probe_ms", "mb", "fpr", "fdr", "false_negatives"])

    rows = tiled(s, d).df.select("tile", "x", "y").groupBy("tile").applyInPandas(run, "kind string, build_s double, probe_ms double, mb double, fpr double, fdr double, false_negatives double")
    return rows.groupBy("kind").agg(*(F.sum(c).alias(c) for c in ("build_s", "mb", "false_negatives")), *(F.avg(c).alias(c) for c in ("probe_ms", "fpr", "fdr")))


query("baseline_index_probe", _probe)

# tiles, filters, planner, measures --------------------------------------------------------------


def _grid(s: SparkSession, d: str) -> DataFrame:
    tm = TileMap.grid((0.0, 0.0, 2600000.0, 2600000.0), 4, 4)
    box = tm.finite_boxes()
    pick = lambda k: F.get(F.array(*(F.lit(int(b[k] // 650000)) for b in box)), F.col("tile"))
    points = pl.events(s, d).withColumn("tile", tm.tile_of(F.col("x"), F.col("y")))
    return points.select("pid", pick(0).alias("gx"), pick(1).alias("gy"))


_CELL = "CAST(least(3, greatest(0, floor({c} / 650000e0))) AS INTEGER)"
query("tile_assignment_grid", _grid, f"SELECT pid, {_CELL.format(c='x')} AS gx, {_CELL.format(c='y')} AS gy FROM {E}")
query("tile_balance_grid", lambda s, d: _grid(s, d).groupBy("gx", "gy").agg(F.count(F.lit(1)).alias("n")), f"SELECT gx, gy, count(*) AS n FROM (SELECT {_CELL.format(c='x')} AS gx, {_CELL.format(c='y')} AS gy FROM {E}) GROUP BY gx, gy")


def _balance(s: SparkSession, d: str) -> DataFrame:
    rows = [(k, *(float(v) for v in metrics.balance(tiled(s, d, kind=k).counts).values())) for k in ("kd", "str", "quadtree", "grid")]
    return s.createDataFrame(rows, "kind string, max_over_mean double, gini double, top5_share double")


query("tile_balance_report", _balance)
_STEP = 20000


def _occupied(points: DataFrame) -> DataFrame:
    return points.select(F.floor(F.col("x") / _STEP).alias("gx"), F.floor(F.col("y") / _STEP).alias("gy")).distinct()


query("occupied_cells", lambda s, d: _occupied(pl.events(s, d)), f"SELECT DISTINCT CAST(floor(x / {_STEP}e0) AS BIGINT) AS gx, CAST(floor(y / {_STEP}e0) AS BIGINT) AS gy FROM {E}")


def _cells(s: SparkSession) -> DataFrame:
    """A window in each cell of a 130 x 130 grid, a little smaller than the cell, as it is half-open."""
    c = s.range(130 * 130).select(F.col("id").alias("qid"), (F.col("id") % 130 * _STEP).cast("double").alias("x1"), (F.floor(F.col("id") / 130) * _STEP).cast("double").alias("y1"))
    return c.withColumns({"x2": F.col("x1") + _STEP - 1, "y2": F.col("y1") + _STEP - 1})


query(
    "filter_probe_truth",
    lambda s, d: rangejoin.range_join(_cells(s), tiled(s, d), filter=True, how="anti").agg(F.count(F.lit(1)).alias("n_empty")),
    f"SELECT 16900 - count(*) AS n_empty FROM (SELECT DISTINCT floor(x / {_STEP}e0) AS gx, floor(y / {_STEP}e0) AS gy FROM {E} WHERE x < 2600000 AND y < 2600000)",
)
query("filter_no_false_negative", lambda s, d: metrics.filter_quality(_cells(s), tiled(s, d, with_filters=True)).select(F.col("fn").alias("violations")), "SELECT 0 AS violations")
query("filter_quality", lambda s, d: metrics.filter_quality(_cells(s), tiled(s, d, with_filters=True)))


def _learned(s: SparkSession, d: str) -> DataFrame:
    """Filter quality on the same windows before and after one round of learning, with each border rule, and when shrunk."""
    q = pl.windows_of(pl.events(s, d).withColumns({"x": F.col("x") + 37000, "y": F.col("y") + 410000}), 15000.0, 40)
    tt = tiled(s, d, with_filters=True)
    out = None
    for name, table in (("static", tt), ("keep", rangejoin.adapt(q, tt, "keep")), ("exact", rangejoin.adapt(q, tt)), ("exact_shrunk", rangejoin.adapt(q, tt, max_bits=512))):
        row = metrics.filter_quality(q, table).withColumns({"rule": F.lit(name), "bits": F.lit(table.filters.size_bits)})
        out = row if out is None else out.unionByName(row)
    return out


query("filter_adaptive_round2", _learned)


def _learned_knn(s: SparkSession, d: str) -> DataFrame:
    """Filter quality on windows in empty places before and after a batch of nearest-neighbour queries that found them empty."""
    focal = pl.events(s, d).where("pid % 40 = 0").select(F.col("pid").alias("qid"), (F.col("x") + 37000).alias("cx"), (F.col("y") + 410000).alias("cy"))
    q = focal.select("qid", (F.col("cx") - 4000).alias("x1"), (F.col("cy") - 4000).alias("y1"), (F.col("cx") + 4000).alias("x2"), (F.col("cy") + 4000).alias("y2"))
    tt = tiled(s, d, with_filters=True)
    rows = (metrics.filter_quality(q, x).withColumns({"rule": F.lit(n), "bits": F.lit(x.filters.size_bits)}) for n, x in (("static", tt), ("learned", knnjoin.adapt(focal, tt))))
    return next(rows).unionByName(next(rows))


query("filter_adaptive_knn", _learned_knn)


_SHARES = (("hot", "h1", 88, 150), ("hot", "h2", 112, 225), ("warm", "w1", 100, 125), ("warm", "w2", 100, 125), *((f"cold{i}", "", 200, 125) for i in range(3)))
"""The worked example's parts: their tile, and how many of a thousand events are their data and their queries."""


def _example(s: SparkSession, d: str) -> DataFrame:
    """The worked example on all events, dealt to its tiles by their ids and counted there, in units of 250 data and 80 queries."""
    at = F.col("pid") % 1000

    def part(k: int):
        ends = np.cumsum([p[k] for p in _SHARES])
        return F.coalesce(*(F.when(at < int(e), i) for i, e in enumerate(ends)))

    rows = pl.events(s, d).groupBy(part(2).alias("data"), part(3).alias("asked")).agg(F.count(F.lit(1)).alias("n")).collect()  # a row a pair of parts
    n = sum(r["n"] for r in rows)
    of = lambda c, i, unit: sum(r["n"] for r in rows if r[c] == i) * unit / n
    found = [(tile, name, Tile(of("data", i, 250), of("asked", i, 80))) for i, (tile, name, *_) in enumerate(_SHARES)]
    parts, whole = {}, {}
    for tile, name, t in found:
        parts.setdefault(tile, []).append((name, t))
        whole[tile] = Tile(whole[tile].n_data + t.n_data, whole[tile].n_query + t.n_query) if tile in whole else t
    trail = planner.greedy(list(whole.items()), lambda h, k: parts[h] if k == len(parts.get(h, [])) == 2 else [], 5).costs
    return s.createDataFrame([(i, round(c, 2)) for i, c in enumerate(trail)], "step int, cost double")


query("planner_running_example", _example, "SELECT * FROM (VALUES (0, 340e0), (1, 225e0), (2, 132.36e0)) AS t(step, cost)")


def _costs(s: SparkSession, d: str) -> DataFrame:
    rows = [(by, area, i, float(c)) for by in ("query", "data", "product") for area in ("a", "c") for i, c in enumerate(rangejoin.modelled_costs(pl.windows_of(pl.events(s, d), 20000.0, 5, area), tiled(s, d), by=by))]
    return s.createDataFrame(rows, "cut_by string, area string, step int, cost double")


query("planner_cost_before_after", _costs)


def _sampled_costs(s: SparkSession, d: str) -> DataFrame:
    """The same with the local work estimated from samples, and with weights in seconds from timed local joins."""
    rows = []
    for plane, q in (("E", pl.windows_of(pl.events(s, d), 20000.0, 5, "a")), ("L", _l_windows(s, d, "l_orderkey % 20 = 0"))):
        tt = tiled(s, d, plane)
        pairs = rangejoin.sampled_pairs(q, tt)
        for name, model in (("sampled", CostModel(p_probe=1.0, p_pair=1.0)), ("calibrated", rangejoin.calibrated(q, tt))):
            rows += [(plane, name, i, float(c)) for i, c in enumerate(rangejoin.modelled_costs(q, tt, model=model, pairs=pairs))]
    return s.createDataFrame(rows, "plane string, model string, step int, cost double")


query("planner_cost_sampled", _sampled_costs)


def _tile_times(s: SparkSession, d: str) -> DataFrame:
    """How long each tile's local join took, before and after the plan's cuts."""
    q = _l_windows(s, d, "l_orderkey % 20 = 0 AND x BETWEEN 1000000 AND 1800000 AND y BETWEEN 2000000 AND 2800000")
    tt = tiled(s, d, "L")
    named = (rangejoin.tile_times(q, x).select(F.lit(n).alias("plan"), "*") for n, x in (("none", tt), ("query", rangejoin.planned(q, tt))))
    return next(named).unionByName(next(named))


query("straggler_tile_times", _tile_times)


def _straggler_report(s: SparkSession, d: str) -> DataFrame:
    """Per plan: the mean of the five slowest tiles, and the share of tiles under a tenth of the slowest one's time."""
    t = _tile_times(s, d).withColumn("place", F.row_number().over(Window.partitionBy("plan").orderBy(F.desc("seconds"))))
    most = F.max("seconds").over(Window.partitionBy("plan"))
    t = t.withColumn("quick", (F.col("seconds") < most / 10).cast("double"))
    return t.groupBy("plan").agg(F.avg(F.when(F.col("place") <= 5, F.col("seconds"))).alias("top5_mean_s"), F.avg("quick").alias("share_under"), F.sum("pairs").alias("pairs"), F.count(F.lit(1)).alias("tiles"))


query("straggler_report", _straggler_report)


def _shuffle(s: SparkSession, d: str, kind: str) -> DataFrame:
    tt = tiled(s, d, with_filters=True)
    if kind == "range":
        q = pl.windows_of(pl.events(s, d).withColumn("y", F.col("y") + 300000), 20000.0, 10)
        rows = [(f, metrics.routed_records(q, tt, f)) for f in (False, True)]
    else:
        q = _f(s, d).withColumn("r2", route.bound_from_counts(F.col("cx"), F.col("cy"), tt.tiles, tt.counts, F.lit(30)))
        rows = [(f, route.circles(q, tt.tiles, F.col("r2"), tt.filters if f else None).count()) for f in (False, True)]
    return s.createDataFrame(rows, "filtered boolean, routed long")


query("shuffle_cost_range", lambda s, d: _shuffle(s, d, "range"))
query("shuffle_cost_knn", lambda s, d: _shuffle(s, d, "knn"))
query("visited_tiles_report", lambda s, d: metrics.visited_tiles(pl.windows_of(pl.events(s, d), 20000.0, 10), tiled(s, d, with_filters=True), True).groupBy("n_tiles").agg(F.count(F.lit(1)).alias("n_queries")))

# shapes -----------------------------------------------------------------------------------------


def _order_boxes(s: SparkSession, d: str, every: int) -> DataFrame:
    p = pl.lineitem(s, d, "l_orderkey").where(F.col("l_orderkey") % every == 0)
    b = p.groupBy("l_orderkey").agg(F.min("x").alias("x1"), F.min("y").alias("y1"), F.max("x").alias("x2"), F.max("y").alias("y2"))
    return b.select(*shapes.rect_shape(F.col("l_orderkey"), F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2")))


_BOXES = "(SELECT l_orderkey AS sid, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM {l} WHERE l_orderkey % {m} = 0 GROUP BY l_orderkey)"
_MEET = f"SELECT a.sid AS asid, b.sid AS bsid FROM {_BOXES.format(l=L, m=97)} a JOIN {_BOXES.format(l=L, m=1)} b ON a.x1 <= b.x2 AND b.x1 <= a.x2 AND a.y1 <= b.y2 AND b.y1 <= a.y2"
query("shape_intersects_rects", lambda s, d: shapes.shape_join(_order_boxes(s, d, 97), _order_boxes(s, d, 1), exact=False), _MEET)
query("shape_intersects_tiles", lambda s, d: shapes.tile_shape_join(_order_boxes(s, d, 97), _order_boxes(s, d, 1), tiled(s, d, "L").tiles, exact=False), _MEET)
query("shape_intersects_dual_tree", lambda s, d: shapes.tile_shape_join(_order_boxes(s, d, 97), _order_boxes(s, d, 1), tiled(s, d, "L").tiles, exact=False, local="auto"), _MEET)
query(
    "shape_window_rects",
    lambda s, d: shapes.shape_search(_order_boxes(s, d, 1), 2000000.0, 4000000.0, 2500000.0, 4500000.0).select("sid"),
    f"SELECT sid FROM {_BOXES.format(l=L, m=1)} WHERE x1 <= 2500000 AND 2000000 <= x2 AND y1 <= 4500000 AND 4000000 <= y2",
)
query("shape_polyline_window", lambda s, d: shapes.shape_search(shapes.paths(pl.events(s, d, "user_id", "ts")), 600000.0, 900000.0, 700000.0, 1000000.0).select("sid"))


def _paths_boxes(s: SparkSession, d: str) -> DataFrame:
    lines = shapes.paths(pl.events(s, d, "user_id", "ts"))
    boxes = s.createDataFrame([(i, 500000.0 * i, 200000.0, 500000.0 * i + 60000, 500000.0) for i in range(5)], "sid long, x1 double, y1 double, x2 double, y2 double")
    return shapes.shape_join(lines, boxes.select(*shapes.rect_shape(*(F.col(c) for c in ("sid", "x1", "y1", "x2", "y2")))), cell=300000.0)


query("shape_join_paths_boxes", _paths_boxes)
