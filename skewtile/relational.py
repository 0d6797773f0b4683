"""What users put around the methods: scans, predicates, joins, aggregates, windows, set operations, functions, subqueries, streams, UDFs.

Each is a query over the given tables with its DuckDB SQL where SQL can say it.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from skewtile import sqlsurface
from skewtile.functions import curves
from skewtile.functions import geometry as g
from skewtile.operators import rangejoin, shapes
from skewtile.operators.tiled import TiledTable
from skewtile.sources import formats, generator
from skewtile.sources import planes as pl
from skewtile.streaming import streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
E, L, O = pl.SQL["E"], pl.SQL["L"], pl.SQL["O"]  # noqa: E741
C, col, lit = F.col, F.col, F.lit
_AREA = "CASE " + " ".join(f"WHEN x BETWEEN {b[0]:.0f} AND {b[2]:.0f} AND y BETWEEN {b[1]:.0f} AND {b[3]:.0f} THEN '{n}'" for n, b in reversed(pl.AREAS.items())) + " ELSE 'rest' END"
_QA = pl.windows_sql("E", 20000, 5, "a")
_IN = "d.x BETWEEN q.x1 AND q.x2 AND d.y BETWEEN q.y1 AND q.y2"


def query(name: str, sql: str | None = None):
    def put(run):
        QUERIES[name] = run
        if sql:
            SQL[name] = sql
        return run

    return put


def ev(s: SparkSession, d: str) -> DataFrame:
    """Plane E with all its payload."""
    return pl.events(s, d, "user_id", "event_type", "ts", "value", "props")


def qa(s: SparkSession, d: str) -> DataFrame:
    return pl.windows_of(pl.events(s, d), 20000.0, 5, "a")


def qall(s: SparkSession, d: str) -> DataFrame:
    return pl.windows_of(pl.events(s, d), 20000.0, 50)


def hits(s: SparkSession, d: str) -> DataFrame:
    """(qid, pid) of the windows of area a."""
    return rangejoin.range_join(qa(s, d), TiledTable.build(pl.events(s, d), 8))


_HITS = f"(SELECT q.qid, d.pid FROM {_QA} q JOIN {E} d ON {_IN})"


def cells(df: DataFrame, side: float = 200000.0) -> DataFrame:
    return df.withColumns({"gx": F.floor(col("x") / side), "gy": F.floor(col("y") / side)})


_CELLS = f"(SELECT *, CAST(floor(x / 200000e0) AS BIGINT) AS gx, CAST(floor(y / 200000e0) AS BIGINT) AS gy FROM {E})"

# scans, sources, sinks --------------------------------------------------------------------------


@query("scan_points", "SELECT l_orderkey, l_linenumber FROM lineitem WHERE round(l_extendedprice * 100) BETWEEN 2000000 AND 2200000")
def _(s, d):
    return formats.window_scan(pl.table(s, d, "lineitem"), 2000000, 2200000).select("l_orderkey", "l_linenumber")


for _kind in ("csv", "json", "orc"):
    query(f"{_kind}_roundtrip", f"SELECT * FROM {_QA}")(lambda s, d, k=_kind: formats.round_trip(qa(s, d), k, formats.RECT_SCHEMA))


@query("tiled_parquet_roundtrip", f"SELECT pid, x, y FROM {E} WHERE floor(x / 650000e0) IN (0, 2)")
def _(s, d):
    return formats.tiled_round_trip(pl.events(s, d).withColumn("tile", F.floor(col("x") / 650000).cast("int")), [0, 2]).select("pid", "x", "y")


@query("generated_queries", generator.generated_sql(E))
def _(s, d):
    return generator.generated_from(pl.events(s, d))


@query("values_inline", f"SELECT v.name, count(*) AS n FROM (VALUES ('a', 600000, 0, 900000, 300000), ('b', 1500000, 0, 1700000, 200000)) AS v(name, x1, y1, x2, y2) JOIN {E} d ON d.x BETWEEN v.x1 AND v.x2 AND d.y BETWEEN v.y1 AND v.y2 GROUP BY v.name")
def _(s, d):
    pl.events(s, d).createOrReplaceTempView("plane_e")
    return s.sql("SELECT v.name, count(*) AS n FROM VALUES ('a', 600000, 0, 900000, 300000), ('b', 1500000, 0, 1700000, 200000) AS v(name, x1, y1, x2, y2) JOIN plane_e d ON d.x BETWEEN v.x1 AND v.x2 AND d.y BETWEEN v.y1 AND v.y2 GROUP BY v.name")


def _wkb_points(s, d):
    w = pl.events(s, d).select("pid", shapes.point_wkb(col("x"), col("y")).alias("wkb"))
    return w.withColumn("p", shapes.wkb_point(col("wkb"))).select("pid", "p.x", "p.y")


query("wkb_points", f"SELECT pid, x, y FROM {E}")(_wkb_points)


# projections and predicates ---------------------------------------------------------------------

for _p in pl.PLANES:
    query(f"project_points_{_p.lower()}", f"SELECT pid, x, y FROM {pl.SQL[_p]}")(lambda s, d, p=_p: pl.PLANES[p](s, d))
_FILTERS = {
    "filter_window": ("x BETWEEN 500000 AND 800000 AND y BETWEEN 0 AND 200000",) * 2,
    "filter_circle": ("(x - 700000) * (x - 700000) + (y - 100000) * (y - 100000) <= 1e10",) * 2,
    "filter_window_attr": ("x BETWEEN 500000 AND 900000 AND y BETWEEN 0 AND 400000 AND event_type = 'click' AND value > 10",) * 2,
    "filter_or_windows": ("(x BETWEEN 0 AND 100000 AND y BETWEEN 0 AND 100000) OR (x BETWEEN 2000000 AND 2100000 AND y BETWEEN 0 AND 300000)",) * 2,
    "filter_not_window": ("NOT (x BETWEEN 100000 AND 2500000 AND y BETWEEN 0 AND 900000)",) * 2,
    "filter_tile_in": ("CAST(floor(x / 650000) AS INT) IN (1, 3)", "CAST(floor(x / 650000e0) AS INTEGER) IN (1, 3)"),
    "sample_mod": ("pid % 17 = 5",) * 2,
}
for _n, (_a, _b) in _FILTERS.items():
    query(_n, f"SELECT pid, x, y FROM {E} WHERE {_b}")(lambda s, d, a=_a: ev(s, d).where(a).select("pid", "x", "y"))


@query("filter_text_like", "SELECT doc_id FROM documents WHERE text LIKE '%the%' AND regexp_matches(text, '[0-9]{3}') AND contains(lower(text), 'and')")
def _(s, d):
    return pl.table(s, d, "documents").where(col("text").like("%the%") & col("text").rlike("[0-9]{3}") & F.lower("text").contains("and")).select("doc_id")


@query("area_label", f"SELECT pid, {_AREA} AS area FROM {E}")
def _(s, d):
    return pl.events(s, d).select("pid", streams.area_label().alias("area"))


@query("null_safe_points", f"SELECT pid, coalesce(nullif(x, 7), 0) AS x0, (nullif(pid % 3, 0) IS NOT DISTINCT FROM nullif(pid % 5, 0)) AS same FROM {E} WHERE nullif(pid % 4, 0) IS NOT NULL")
def _(s, d):
    p = pl.events(s, d).withColumn("k", F.nullif(col("pid") % 4, lit(0))).dropna(subset=["k"])
    return p.select("pid", F.coalesce(F.nanvl(F.nullif(col("x"), lit(7.0)), lit(0.0)), lit(0.0)).alias("x0"), F.nullif(col("pid") % 3, lit(0)).eqNullSafe(F.nullif(col("pid") % 5, lit(0))).alias("same"))


@query("distinct_windows", f"SELECT DISTINCT floor(x1 / 50000e0) AS a, floor(y1 / 50000e0) AS b FROM {_QA}")
def _(s, d):
    return qa(s, d).select(F.floor(col("x1") / 50000).cast("double").alias("a"), F.floor(col("y1") / 50000).cast("double").alias("b")).dropDuplicates(["a", "b"])


# joins ------------------------------------------------------------------------------------------


@query("join_broadcast_nation", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(s, d):
    # nation and region are tables of fixed size
    return pl.table(s, d, "customer").join(F.broadcast(pl.table(s, d, "nation")), col("c_nationkey") == col("n_nationkey")).groupBy("n_name").agg(F.count(lit(1)).alias("n"))


for _n, _hint in (("join_smj_orders", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    query(_n, "SELECT o_orderstatus, count(*) AS n, sum(l_quantity) AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus")(
        lambda s, d, h=_hint: pl.table(s, d, "lineitem").join(pl.table(s, d, "orders").hint(h), col("o_orderkey") == col("l_orderkey")).groupBy("o_orderstatus").agg(F.count(lit(1)).alias("n"), F.sum("l_quantity").alias("qty"))
    )


@query("join_window_theta", f"SELECT q.qid, d.pid FROM {_QA} q JOIN {E} d ON {_IN}")
def _(s, d):
    # the condition alone has no equal part, and nested loops grow with points times windows: squares of the plane give it one
    q, at = qa(s, d), lambda c: F.floor(col(c) / 10000)
    q = q.withColumn("gx", F.explode(F.sequence(at("x1"), at("x2")))).withColumn("gy", F.explode(F.sequence(at("y1"), at("y2"))))
    near = pl.events(s, d).withColumns({"gx": at("x"), "gy": at("y")}).join(q, ["gx", "gy"])
    return near.where(g.in_rect(col("x"), col("y"), col("x1"), col("y1"), col("x2"), col("y2"))).select("qid", "pid")


@query("join_band_cells", f"SELECT q.qid, d.pid FROM {_QA} q JOIN {E} d ON {_IN}")
def _(s, d):
    return rangejoin.cell_join(pl.events(s, d), qa(s, d), rangejoin.Cells.of(qa(s, d))).select("qid", "pid")


@query("join_distance", f"SELECT q.pid AS qid, d.pid FROM {E} q JOIN {E} d ON (d.x - q.x) * (d.x - q.x) + (d.y - q.y) * (d.y - q.y) <= 4e8 WHERE q.pid % 40 = 0")
def _(s, d):
    w = pl.windows_of(pl.events(s, d), 20000.0, 40)
    near = rangejoin.cell_join(pl.events(s, d), w, rangejoin.Cells.of(w))
    return near.where(g.dist2(col("x"), col("y"), col("x1") + 20000, col("y1") + 20000) <= 4e8).select("qid", "pid")


@query("join_interval", f"SELECT a.pid AS apid, b.pid AS bpid FROM {E} a JOIN {E} b ON b.x BETWEEN a.x AND a.x + 1800 AND b.y BETWEEN a.y - 20000 AND a.y + 20000 AND a.pid <> b.pid WHERE a.pid % 20 = 0")
def _(s, d):
    w = pl.events(s, d).where("pid % 20 = 0").select(col("pid").alias("qid"), col("x").alias("x1"), (col("y") - 20000).alias("y1"), (col("x") + 1800).alias("x2"), (col("y") + 20000).alias("y2"))
    return rangejoin.cell_join(pl.events(s, d), w, rangejoin.Cells.of(w)).where("qid <> pid").select(col("qid").alias("apid"), col("pid").alias("bpid"))


@query("join_asof", "SELECT a.event_id AS buy, (SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'click' AND b.ts = (SELECT max(c.ts) FROM events c WHERE c.user_id = a.user_id AND c.event_type = 'click' AND c.ts <= a.ts)) AS click FROM events a WHERE a.event_type = 'purchase'")
def _(s, d):
    """The user's latest click not after each purchase, by one pass over both kinds in time order."""
    e = pl.table(s, d, "events").where(col("event_type").isin("purchase", "click"))
    kind = F.when(col("event_type") == "click", 0).otherwise(1)
    w = Window.partitionBy("user_id").orderBy("ts", kind, "event_id").rowsBetween(Window.unboundedPreceding, 0)
    e = e.withColumn("click", F.last(F.when(col("event_type") == "click", col("event_id")), ignorenulls=True).over(w))
    return e.where("event_type = 'purchase'").select(col("event_id").alias("buy"), "click")


_SHIFT = "(SELECT pid AS qid, x + 20000 AS x1, y + 290000 AS y1, x + 40000 AS x2, y + 310000 AS y2 FROM " + E + " WHERE pid % 10 = 0)"


def _shifted(s, d):
    p = pl.events(s, d).where("pid % 10 = 0")
    return p.select(col("pid").alias("qid"), (col("x") + 20000).alias("x1"), (col("y") + 290000).alias("y1"), (col("x") + 40000).alias("x2"), (col("y") + 310000).alias("y2"))


@query("semi_hit_queries", f"SELECT q.qid FROM {_SHIFT} q WHERE EXISTS (SELECT 1 FROM {E} d WHERE {_IN})")
def _(s, d):
    q = _shifted(s, d)
    return q.join(rangejoin.cell_join(pl.events(s, d), q, rangejoin.Cells.of(q)).select("qid"), "qid", "left_semi").select("qid")


@query("anti_empty_queries", f"SELECT q.qid FROM {_SHIFT} q WHERE NOT EXISTS (SELECT 1 FROM {E} d WHERE {_IN})")
def _(s, d):
    q = _shifted(s, d)
    return q.join(rangejoin.cell_join(pl.events(s, d), q, rangejoin.Cells.of(q)).select("qid"), "qid", "left_anti").select("qid")


@query("left_hit_counts", f"SELECT q.qid, count(d.pid) AS n FROM {_SHIFT} q LEFT JOIN {E} d ON {_IN} GROUP BY q.qid")
def _(s, d):
    q = _shifted(s, d)
    n = rangejoin.cell_join(pl.events(s, d), q, rangejoin.Cells.of(q)).groupBy("qid").agg(F.count("pid").alias("n"))
    return q.select("qid").join(n, "qid", "left").na.fill(0, ["n"])


@query("full_outer_tiles", f"SELECT coalesce(a.gx, b.gx) AS gx, coalesce(a.n, 0) AS clicks, coalesce(b.n, 0) AS buys FROM (SELECT gx, count(*) AS n FROM {_CELLS} WHERE event_type = 'click' AND gx < 9 GROUP BY gx) a FULL JOIN (SELECT gx, count(*) AS n FROM {_CELLS} WHERE event_type = 'purchase' AND gx > 2 GROUP BY gx) b ON a.gx = b.gx")
def _(s, d):
    c = cells(ev(s, d))
    a = c.where("event_type = 'click' AND gx < 9").groupBy("gx").agg(F.count(lit(1)).alias("clicks"))
    b = c.where("event_type = 'purchase' AND gx > 2").groupBy("gx").agg(F.count(lit(1)).alias("buys"))
    return a.join(b, "gx", "full").na.fill(0, ["clicks", "buys"])


@query("right_outer_tiles", f"SELECT n.k, coalesce(a.n, 0) AS n FROM (SELECT gx, count(*) AS n FROM {_CELLS} GROUP BY gx) a RIGHT JOIN (SELECT range AS k FROM range(20)) n ON a.gx = n.k")
def _(s, d):
    a = cells(pl.events(s, d)).groupBy("gx").agg(F.count(lit(1)).alias("n"))
    return a.join(s.range(20).withColumnRenamed("id", "k"), col("gx") == col("k"), "right").select("k", F.coalesce("n", lit(0)).alias("n"))


@query("self_close_pairs", f"SELECT a.pid AS p, b.pid AS q FROM {E} a JOIN {E} b ON a.pid < b.pid AND b.x BETWEEN a.x - 2000 AND a.x + 2000 AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 4e6")
def _(s, d):
    e = pl.events(s, d)
    w = e.select(col("pid").alias("qid"), (col("x") - 2000).alias("x1"), (col("y") - 2000).alias("y1"), (col("x") + 2000).alias("x2"), (col("y") + 2000).alias("y2"))
    near = rangejoin.cell_join(e, w, rangejoin.Cells.of(w)).where((col("qid") < col("pid")) & (g.dist2(col("x"), col("y"), col("x1") + 2000, col("y1") + 2000) <= 4e6))
    return near.select(col("qid").alias("p"), col("pid").alias("q"))


@query("cross_small", "SELECT r_name, n_name FROM region CROSS JOIN nation")
def _(s, d):
    return pl.table(s, d, "region").crossJoin(pl.table(s, d, "nation")).select("r_name", "n_name")


@query("join_null_safe", "SELECT a.k, a.n AS an, b.n AS bn FROM (SELECT nullif(pid % 4, 0) AS k, count(*) AS n FROM " + E + " GROUP BY 1) a JOIN (SELECT nullif(pid % 6, 0) AS k, count(*) AS n FROM " + E + " GROUP BY 1) b ON a.k IS NOT DISTINCT FROM b.k")
def _(s, d):
    one = lambda m, n: pl.events(s, d).groupBy(F.nullif(col("pid") % m, lit(0)).alias("k" + n)).agg(F.count(lit(1)).alias(n))
    a, b = one(4, "an"), one(6, "bn")
    return a.join(b, col("kan").eqNullSafe(col("kbn"))).select(col("kan").alias("k"), "an", "bn")


@query("join_hits_star", f"SELECT n_name, count(*) AS n FROM {O} o JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE o.x BETWEEN 10000000 AND 20000000 AND o.y BETWEEN 0 AND 20000000 GROUP BY n_name")
def _(s, d):
    o = pl.orders(s, d, "o_custkey").where(g.in_rect(col("x"), col("y"), 10000000, 0, 20000000, 20000000))
    return o.join(pl.table(s, d, "customer"), col("o_custkey") == col("c_custkey")).join(F.broadcast(pl.table(s, d, "nation")), col("c_nationkey") == col("n_nationkey")).groupBy("n_name").agg(F.count(lit(1)).alias("n"))


# aggregates -------------------------------------------------------------------------------------


def agg(name: str, sql: str | None, keys: list, **out):
    query(name, sql)(lambda s, d: cells(ev(s, d)).withColumn("area", streams.area_label()).groupBy(*keys).agg(*(f().alias(n) for n, f in out.items())))


_LAB = f"(SELECT *, {_AREA} AS area FROM {_CELLS})"
agg("tile_stats", f"SELECT gx, gy, count(*) AS n, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM {_CELLS} GROUP BY gx, gy", ["gx", "gy"], n=lambda: F.count(lit(1)), x1=lambda: F.min("x"), y1=lambda: F.min("y"), x2=lambda: F.max("x"), y2=lambda: F.max("y"))
agg("agg_distinct_users", f"SELECT area, count(DISTINCT user_id) AS users FROM {_LAB} GROUP BY area", ["area"], users=lambda: F.countDistinct("user_id"))
agg("agg_approx_distinct", None, ["area"], users=lambda: F.approx_count_distinct("user_id", 0.02))
agg("agg_percentiles", f"SELECT area, quantile_cont(x, 0.5) AS p50, quantile_cont(y, 0.9) AS p90 FROM {_LAB} GROUP BY area", ["area"], p50=lambda: F.percentile("x", 0.5), p90=lambda: F.percentile("y", 0.9))
agg("agg_approx_percentiles", None, ["area"], p50=lambda: F.percentile_approx("x", 0.5), n=lambda: F.count(lit(1)))
agg("agg_moments", f"SELECT area, round(stddev_samp(x), 4) AS sd, round(corr(x, y), 8) AS r, round(covar_samp(x, y) / 1e6, 4) AS cov FROM {_LAB} GROUP BY area", ["area"], sd=lambda: F.round(F.stddev_samp("x"), 4), r=lambda: F.round(F.corr("x", "y"), 8), cov=lambda: F.round(F.covar_samp("x", "y") / 1e6, 4))
agg("agg_max_by", f"SELECT gx, arg_max(pid, x * 1e7 + pid) AS last, arg_min(pid, x * 1e7 + pid) AS first FROM {_CELLS} GROUP BY gx", ["gx"], last=lambda: F.max_by("pid", col("x") * 1e7 + col("pid")), first=lambda: F.min_by("pid", col("x") * 1e7 + col("pid")))
agg("agg_filter_clause", f"SELECT area, count(*) FILTER (WHERE event_type = 'click') AS clicks, sum(CASE WHEN event_type = 'purchase' THEN y ELSE 0 END) AS bought FROM {_LAB} GROUP BY area", ["area"], clicks=lambda: F.count_if(col("event_type") == "click"), bought=lambda: F.sum(F.when(col("event_type") == "purchase", col("y")).otherwise(0.0)))


@query("collect_hits", f"SELECT qid, list_sort(list(pid)) AS pids FROM {_HITS} GROUP BY qid")
def _(s, d):
    return hits(s, d).groupBy("qid").agg(F.sort_array(F.collect_list("pid")).alias("pids"))


for _n in ("cube", "rollup"):
    query(f"{_n}_area_type", f"SELECT area, event_type, count(*) AS n FROM {_LAB} GROUP BY {_n.upper()} (area, event_type)")(lambda s, d, n=_n: getattr(ev(s, d).withColumn("area", streams.area_label()), n)("area", "event_type").agg(F.count(lit(1)).alias("n")))


@query("grouping_sets_area_type", f"SELECT area, event_type, grouping(area) * 2 + grouping(event_type) AS gid, count(*) AS n FROM {_LAB} GROUP BY GROUPING SETS ((area), (event_type), ())")
def _(s, d):
    e = ev(s, d).withColumn("area", streams.area_label())
    return e.groupingSets([[col("area")], [col("event_type")], []], "area", "event_type").agg(F.grouping_id().alias("gid"), F.count(lit(1)).alias("n"))


@query("pivot_type", f"SELECT area, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM {_LAB} GROUP BY area")
def _(s, d):
    return ev(s, d).withColumn("area", streams.area_label()).groupBy("area").pivot("event_type", ["click", "purchase"]).agg(F.count(lit(1))).na.fill(0, ["click", "purchase"])


@query("unpivot_stats", f"SELECT gx, k, v FROM (SELECT gx, min(x) AS low, max(x) AS high FROM {_CELLS} GROUP BY gx) UNPIVOT (v FOR k IN (low, high))")
def _(s, d):
    t = cells(pl.events(s, d)).groupBy("gx").agg(F.min("x").alias("low"), F.max("x").alias("high"))
    return t.unpivot("gx", ["low", "high"], "k", "v")


@query("occupied_cell_bitmap", f"SELECT count(DISTINCT gx * 20 + gy) AS n FROM {_CELLS}")
def _(s, d):
    """Cells as bits: bitmaps by bucket, then counted."""
    p = cells(pl.events(s, d)).select((col("gx") * 20 + col("gy")).alias("c"))
    b = p.groupBy(F.bitmap_bucket_number("c").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("c")).alias("bits"))
    return b.agg(F.sum(F.bitmap_count("bits")).alias("n"))


@query("agg_having_hot", f"SELECT gx, gy, count(*) AS n FROM {_CELLS} GROUP BY gx, gy HAVING count(*) > 100")
def _(s, d):
    return cells(pl.events(s, d)).groupBy("gx", "gy").agg(F.count(lit(1)).alias("n")).where("n > 100")


@query("agg_decimal_revenue", "SELECT l_returnflag, CAST(sum(CAST(round(l_extendedprice, 2) AS DECIMAL(18,2))) AS VARCHAR) AS revenue FROM lineitem GROUP BY l_returnflag")
def _(s, d):
    return pl.table(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.round("l_extendedprice", 2).cast("decimal(18,2)")).cast("string").alias("revenue"))


# windows ----------------------------------------------------------------------------------------


def _ranked(s, d):
    """The hits of area a with their squared distance from the window's middle."""
    q = qa(s, d)
    return rangejoin.cell_join(pl.events(s, d), q, rangejoin.Cells.of(q)).withColumn("d2", g.dist2(col("x"), col("y"), col("x1") + 20000, col("y1") + 20000)).select("qid", "pid", "d2")


_RANKED = f"(SELECT q.qid, d.pid, (d.x - q.x1 - 20000) * (d.x - q.x1 - 20000) + (d.y - q.y1 - 20000) * (d.y - q.y1 - 20000) AS d2 FROM {_QA} q JOIN {E} d ON {_IN})"


def _byq():
    return Window.partitionBy("qid").orderBy("d2", "pid")


@query("rank_by_distance", f"SELECT qid, pid, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM {_RANKED} WINDOW w AS (PARTITION BY qid ORDER BY d2, pid), v AS (PARTITION BY qid ORDER BY d2)")
def _(s, d):
    v = Window.partitionBy("qid").orderBy("d2")
    return _ranked(s, d).select("qid", "pid", F.row_number().over(_byq()).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"))


@query("dist_rank_tile", f"SELECT qid, pid, ntile(4) OVER w AS q4, round(percent_rank() OVER w, 8) AS pr, round(cume_dist() OVER w, 8) AS cd FROM {_RANKED} WINDOW w AS (PARTITION BY qid ORDER BY d2, pid)")
def _(s, d):
    return _ranked(s, d).select("qid", "pid", F.ntile(4).over(_byq()).alias("q4"), F.round(F.percent_rank().over(_byq()), 8).alias("pr"), F.round(F.cume_dist().over(_byq()), 8).alias("cd"))


_USER = "PARTITION BY user_id ORDER BY ts, pid"


def _byu():
    return Window.partitionBy("user_id").orderBy("ts", "pid")


@query("path_segments", f"SELECT pid, x, y, tx, ty FROM (SELECT pid, x, y, lead(x) OVER w AS tx, lead(y) OVER w AS ty FROM {E} WINDOW w AS ({_USER})) WHERE tx IS NOT NULL")
def _(s, d):
    return shapes.segments(ev(s, d)).select("pid", "x", "y", col("to_x").alias("tx"), col("to_y").alias("ty"))


@query("path_length", f"SELECT pid, round(coalesce(sum(step) OVER (PARTITION BY user_id ORDER BY ts, pid ROWS UNBOUNDED PRECEDING), 0), 3) AS gone FROM (SELECT *, abs(x - lag(x) OVER w) + abs(y - lag(y) OVER w) AS step FROM {E} WINDOW w AS ({_USER}))")
def _(s, d):
    e = ev(s, d).withColumn("step", F.abs(col("x") - F.lag("x").over(_byu())) + F.abs(col("y") - F.lag("y").over(_byu())))
    return e.select("pid", F.round(F.coalesce(F.sum("step").over(_byu().rowsBetween(Window.unboundedPreceding, 0)), lit(0.0)), 3).alias("gone"))


@query("prefix_weight", f"SELECT gx, gy, sum(n) OVER (PARTITION BY gx ORDER BY gy ROWS UNBOUNDED PRECEDING) AS upto FROM (SELECT gx, gy, count(*) AS n FROM {_CELLS} GROUP BY gx, gy)")
def _(s, d):
    c = cells(pl.events(s, d)).groupBy("gx", "gy").agg(F.count(lit(1)).alias("n"))
    return c.select("gx", "gy", F.sum("n").over(Window.partitionBy("gx").orderBy("gy").rowsBetween(Window.unboundedPreceding, 0)).alias("upto"))


@query("moving_avg_value", f"SELECT pid, round(avg(y) OVER (PARTITION BY user_id ORDER BY ts, pid ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 4) AS m FROM {E}")
def _(s, d):
    return ev(s, d).select("pid", F.round(F.avg("y").over(_byu().rowsBetween(-3, 0)), 4).alias("m"))


@query("range_frame_count", f"SELECT pid, count(*) OVER (PARTITION BY event_type ORDER BY x RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING) AS n FROM {E}")
def _(s, d):
    return ev(s, d).select("pid", F.count(lit(1)).over(Window.partitionBy("event_type").orderBy("x").rangeBetween(-1000, 1000)).alias("n"))


@query("first_last_value", f"SELECT pid, first_value(pid) OVER w AS a, last_value(pid) OVER w AS b, nth_value(pid, 2) OVER w AS c FROM {E} WINDOW w AS ({_USER} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(s, d):
    w = _byu().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return ev(s, d).select("pid", F.first("pid").over(w).alias("a"), F.last("pid").over(w).alias("b"), F.nth_value("pid", 2).over(w).alias("c"))


@query("topk_per_area", f"SELECT area, pid FROM {_LAB} QUALIFY row_number() OVER (PARTITION BY area ORDER BY y DESC, pid) <= 5")
def _(s, d):
    e = ev(s, d).withColumn("area", streams.area_label())
    return e.withColumn("rn", F.row_number().over(Window.partitionBy("area").orderBy(F.desc("y"), "pid"))).where("rn <= 5").select("area", "pid")


# sort, limit, sets ------------------------------------------------------------------------------

_COUNTS = f"(SELECT gx, gy, count(*) AS n FROM {_CELLS} GROUP BY gx, gy)"


@query("topk_hot_tiles", f"SELECT gx, gy, n FROM {_COUNTS} ORDER BY n DESC, gx, gy LIMIT 10")
def _(s, d):
    return cells(pl.events(s, d)).groupBy("gx", "gy").agg(F.count(lit(1)).alias("n")).orderBy(F.desc("n"), "gx", "gy").limit(10)


@query("sorted_page", f"SELECT pid, x FROM {E} ORDER BY x, pid LIMIT 20 OFFSET 40")
def _(s, d):
    return pl.events(s, d).select("pid", "x").orderBy("x", "pid").offset(40).limit(20)


_W1, _W2 = "x BETWEEN 500000 AND 800000 AND y BETWEEN 0 AND 200000", "x BETWEEN 700000 AND 900000 AND y BETWEEN 100000 AND 300000"
for _n, _op, _sql in (("union_hits", "unionByName", "UNION ALL"), ("intersect_hits", "intersect", "INTERSECT"), ("intersect_all_hits", "intersectAll", "INTERSECT ALL"), ("except_hits", "subtract", "EXCEPT"), ("except_all_plans", "exceptAll", "EXCEPT ALL")):
    query(_n, f"SELECT pid FROM {E} WHERE {_W1} {_sql} SELECT pid FROM {E} WHERE {_W2}")(lambda s, d, op=_op: getattr(pl.events(s, d).where(_W1).select("pid"), op)(pl.events(s, d).where(_W2).select("pid")))

# functions --------------------------------------------------------------------------------------


@query("str_key_parse", "SELECT c_custkey, split_part(c_name, '#', 1) AS a, CAST(substr(c_name, -3) AS VARCHAR) AS b, concat_ws('-', lower(c_mktsegment), length(c_name)) AS c, levenshtein(c_mktsegment, 'BUILDING') AS d FROM customer")
def _(s, d):
    return pl.table(s, d, "customer").select("c_custkey", F.split_part("c_name", lit("#"), lit(1)).alias("a"), F.substring("c_name", -3, 3).alias("b"), F.concat_ws("-", F.lower("c_mktsegment"), F.length("c_name").cast("string")).alias("c"), F.levenshtein("c_mktsegment", lit("BUILDING")).alias("d"))


@query("text_payload_hits", "SELECT doc_id, regexp_extract(text, '([A-Za-z]+)', 1) AS word, length(text) AS n FROM documents WHERE contains(text, 'the')")
def _(s, d):
    return pl.table(s, d, "documents").where(F.contains(col("text"), lit("the"))).select("doc_id", F.regexp_extract("text", "([A-Za-z]+)", 1).alias("word"), F.length("text").alias("n"))


@query("url_host_of_pages", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host FROM pages")
def _(s, d):
    return pl.table(s, d, "pages").select("page_id", F.parse_url("url", lit("HOST")).alias("host"))


@query("hourly_query_load", f"SELECT CAST(hour(ts) AS INTEGER) AS h, count(*) AS n FROM {E} GROUP BY 1")
def _(s, d):
    return ev(s, d).groupBy(F.hour("ts").alias("h")).agg(F.count(lit(1)).alias("n"))


@query("ship_month_hits", "SELECT strftime(date_trunc('month', l_shipdate), '%Y-%m') AS m, count(*) AS n FROM lineitem GROUP BY 1")
def _(s, d):
    return pl.table(s, d, "lineitem").groupBy(F.date_format(F.date_trunc("month", "l_shipdate"), "yyyy-MM").alias("m")).agg(F.count(lit(1)).alias("n"))


@query("date_arith", "SELECT o_orderkey, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS d, CAST(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH AS DATE) AS m FROM orders")
def _(s, d):
    return pl.table(s, d, "orders").select("o_orderkey", F.datediff("o_orderdate", lit("1995-01-01").cast("date")).alias("d"), F.add_months(col("o_orderdate").cast("date"), 2).alias("m"))


@query("distance_values", f"SELECT pid, round(sqrt((x - 700000) * (x - 700000) + (y - 100000) * (y - 100000)), 4) AS a, greatest(x, y) AS m, least(x, y) AS l FROM {E}")
def _(s, d):
    return pl.events(s, d).select("pid", F.round(F.hypot(col("x") - 700000, col("y") - 100000), 4).alias("a"), F.greatest("x", "y").alias("m"), F.least("x", "y").alias("l"))


_HAV = "round(2 * 6371000e0 * asin(least(1e0, sqrt(pow(sin((radians(48e0) - radians(y / 1e5)) / 2), 2) + cos(radians(y / 1e5)) * cos(radians(48e0)) * pow(sin((radians(11e0) - radians(x / 1e5)) / 2), 2)))), 3)"


def _haversine(s, d):
    return pl.events(s, d).select("pid", F.round(g.haversine_m(col("x") / 1e5, col("y") / 1e5, lit(11.0), lit(48.0)), 3).alias("m"))


query("haversine", f"SELECT pid, {_HAV} AS m FROM {E}")(_haversine)


_BITS = " + ".join(f"((CAST(floor({c} / 1e4) AS BIGINT) >> {b}) & 1) * {1 << (2 * b + o)}" for o, c in ((0, "x"), (1, "y")) for b in range(10))


@query("morton_codes", f"SELECT pid, {_BITS} AS z FROM {E}")
def _(s, d):
    return pl.events(s, d).select("pid", curves.morton_column(F.floor(col("x") / 1e4), F.floor(col("y") / 1e4)).alias("z"))


@query("cell_histogram", f"SELECT z, count(*) AS n, CAST(bit_count(z) AS INTEGER) AS ones FROM (SELECT ({_BITS}) >> 8 AS z FROM {E}) GROUP BY z")
def _(s, d):
    z = F.shiftright(curves.morton_column(F.floor(col("x") / 1e4), F.floor(col("y") / 1e4)), 8)
    return pl.events(s, d).groupBy(z.alias("z")).agg(F.count(lit(1)).alias("n")).withColumn("ones", F.bit_count("z"))


@query("explode_cells", f"SELECT qid, cx FROM (SELECT qid, unnest(generate_series(CAST(floor(x1 / 40000e0) AS BIGINT), CAST(floor(x2 / 40000e0) AS BIGINT))) AS cx FROM {_QA})")
def _(s, d):
    return qa(s, d).select("qid", F.explode(F.sequence(F.floor(col("x1") / 40000), F.floor(col("x2") / 40000))).alias("cx"))


@query("polyline_length_array", f"SELECT user_id AS sid, round(coalesce(sum(sqrt((tx - x) * (tx - x) + (ty - y) * (ty - y))), 0), 2) AS len FROM (SELECT user_id, x, y, lead(x) OVER w AS tx, lead(y) OVER w AS ty FROM {E} WINDOW w AS ({_USER})) GROUP BY user_id")
def _(s, d):
    return shapes.paths(ev(s, d)).select("sid", F.round(shapes.polyline_length(col("pts")), 2).alias("len"))


@query("polygon_area", f"SELECT l_suppkey AS sid, (max(x) - min(x)) * (max(y) - min(y)) AS area FROM {L} GROUP BY l_suppkey")
def _(s, d):
    b = pl.lineitem(s, d, "l_suppkey").groupBy("l_suppkey").agg(F.min("x").alias("x1"), F.min("y").alias("y1"), F.max("x").alias("x2"), F.max("y").alias("y2"))
    return b.select(*shapes.rect_shape(*(col(c) for c in ("l_suppkey", "x1", "y1", "x2", "y2")))).select("sid", shapes.ring_area(col("pts")).alias("area"))


@query("embedding_dot", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE))), 5) AS n2 FROM embeddings")
def _(s, d):
    sq = F.zip_with("embedding", "embedding", lambda a, b: a.cast("double") * b.cast("double"))
    return pl.table(s, d, "embeddings").select("vec_id", F.round(F.aggregate(sq, lit(0.0), lambda a, v: a + v), 5).alias("n2"))


@query("tile_count_map", f"SELECT gx, list_sort(list(gy)) AS ys, CAST(sum(n) AS BIGINT) AS n FROM {_COUNTS} WHERE n > 50 GROUP BY gx")
def _(s, d):
    c = cells(pl.events(s, d)).groupBy("gx", "gy").agg(F.count(lit(1)).alias("n")).groupBy("gx").agg(F.map_from_entries(F.collect_list(F.struct("gy", "n"))).alias("m"))
    m = c.withColumn("m", F.map_filter("m", lambda k, v: v > 50)).where(F.size("m") > 0)
    return m.select("gx", F.sort_array(F.map_keys("m")).alias("ys"), F.aggregate(F.map_values("m"), lit(0).cast("long"), lambda a, v: a + v).alias("n"))


@query("json_prop_hits", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events WHERE CAST(json_extract(props, '$.k') AS BIGINT) > 50")
def _(s, d):
    k = F.variant_get(F.parse_json("props"), "$.k", "long")
    return pl.table(s, d, "events").where(F.from_json("props", "k long")["k"] > 50).select("event_id", k.alias("k"))


@query("hash_bucket_counts")
def _(s, d):
    return pl.events(s, d).groupBy(F.pmod(F.xxhash64("pid"), lit(16)).alias("bucket")).agg(F.count(lit(1)).alias("n"))


# subqueries -------------------------------------------------------------------------------------


def sub(name: str, spark_sql: str, duck_sql: str):
    def run(s, d):
        cells(ev(s, d)).createOrReplaceTempView("cells_e")
        qa(s, d).createOrReplaceTempView("windows_a")
        return s.sql(spark_sql)

    query(name, duck_sql)(run)


for _n, _text in {
    "scalar_max_tile": "SELECT gx, gy, count(*) AS n FROM {c} GROUP BY gx, gy HAVING count(*) = (SELECT max(n) FROM (SELECT count(*) AS n FROM {c} GROUP BY gx, gy))",
    "exists_hit": "SELECT pid FROM {c} a WHERE pid % 50 = 0 AND EXISTS (SELECT 1 FROM {c} b WHERE b.user_id = a.user_id AND b.pid <> a.pid AND b.gx = a.gx)",
    "in_hot_tiles": "SELECT pid FROM {c} WHERE gx IN (SELECT gx FROM {c} GROUP BY gx HAVING count(*) > 700)",
    "not_in_hot_tiles": "SELECT pid FROM {c} WHERE gy NOT IN (SELECT gy FROM {c} GROUP BY gy HAVING count(*) > 300)",
    "correlated_count": "SELECT qid, (SELECT count(*) FROM {c} e WHERE e.pid = w.qid AND e.gy = 0) AS n FROM {w} w",
    "cte_hot_then_hits": "WITH hot AS (SELECT gx, gy FROM {c} GROUP BY gx, gy HAVING count(*) > 150), hit AS (SELECT e.pid, e.gx FROM {c} e JOIN hot USING (gx, gy)) SELECT gx, count(*) AS n FROM hit GROUP BY gx",
}.items():
    sub(_n, _text.format(c="cells_e", w="windows_a"), _text.format(c=_CELLS, w=_QA))

# streams ----------------------------------------------------------------------------------------

query("stream_tumbling", f"SELECT date_trunc('hour', ts) AS start, {_AREA} AS area, count(*) AS n FROM {E} GROUP BY 1, 2")(streams.tumbling)
query("stream_sliding", f"SELECT start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 15 MINUTES, ts) - INTERVAL 45 MINUTES, time_bucket(INTERVAL 15 MINUTES, ts) - INTERVAL 30 MINUTES, time_bucket(INTERVAL 15 MINUTES, ts) - INTERVAL 15 MINUTES, time_bucket(INTERVAL 15 MINUTES, ts)]) AS start FROM {E}) GROUP BY start")(streams.sliding)
query("stream_session", f"SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, pid ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT user_id, ts, pid, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, pid) < INTERVAL 10 MINUTES THEN 0 ELSE 1 END AS new FROM {E})) GROUP BY user_id, k")(streams.sessions)
query("stream_late", f"SELECT date_trunc('day', ts) AS start, count(*) AS n FROM {E} GROUP BY 1")(streams.late_rows)
query("stream_dedup", f"SELECT pid, x, y FROM {E}")(streams.deduplicated)
query("stream_static_join", f"SELECT q.qid, d.pid FROM {pl.windows_sql('E', 20000, 50)} q JOIN {E} d ON {_IN}")(lambda s, d: streams.static_join(s, d, TiledTable.build(pl.events(s, d), 8)))
query("stream_stream_join", "SELECT a.event_id AS buy, b.event_id AS click FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts <= a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR WHERE a.event_type = 'purchase' AND b.event_type = 'click'")(streams.stream_join)


@query("stream_stateful_load", f"SELECT CAST(least(3, floor(x / 650000e0)) AS INTEGER) AS gx, count(*) AS n FROM {E} GROUP BY 1")
def _(s, d):
    from skewtile.plans.tilemap import TileMap

    tm = TileMap.grid((0.0, 0.0, 2600000.0, 1.0), 4, 1)
    out = streams.stateful_load(s, d, TiledTable(pl.events(s, d), tm, np.zeros(4), 4))
    place = [int(b[0] // 650000) for b in tm.finite_boxes()]
    return out.select(F.get(F.array(*map(lit, place)), col("tile")).alias("gx"), "n")


# user functions ---------------------------------------------------------------------------------


def _area_label(s, d):
    areas = dict(pl.AREAS)

    @F.udf("string")
    def label(x, y):
        return next((n for n, b in areas.items() if b[0] <= x <= b[2] and b[1] <= y <= b[3]), "rest")

    return pl.events(s, d).select("pid", label("x", "y").alias("area"))


query("udf_area_label", f"SELECT pid, {_AREA} AS area FROM {E}")(_area_label)


def _udf_haversine(s, d):
    @F.pandas_udf("double")
    def metres(x: pd.Series, y: pd.Series) -> pd.Series:
        lat, lon = np.radians(y / 1e5), np.radians(x / 1e5)
        a = np.sin((np.radians(48) - lat) / 2) ** 2 + np.cos(lat) * np.cos(np.radians(48)) * np.sin((np.radians(11) - lon) / 2) ** 2
        return 2 * 6371000.0 * np.arcsin(np.minimum(1, np.sqrt(a)))

    return pl.events(s, d).select("pid", F.round(metres("x", "y"), 3).alias("m"))


query("udf_haversine", f"SELECT pid, {_HAV} AS m FROM {E}")(_udf_haversine)


@query("udf_hilbert")
def _(s, d):
    @F.pandas_udf("long")
    def h(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series(curves.hilbert(np.floor(x / 1e4).to_numpy(), np.floor(y / 1e4).to_numpy(), 10))

    return pl.events(s, d).select("pid", h("x", "y").alias("h"))


@query("grouped_map_tile_mbr", f"SELECT gx, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM {_CELLS} GROUP BY gx")
def _(s, d):
    def box(p: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame([(p["gx"].iloc[0], p["x"].min(), p["y"].min(), p["x"].max(), p["y"].max())], columns=["gx", "x1", "y1", "x2", "y2"])

    # a cell's column is first folded to one row a task, so no group holds more than tasks
    part = cells(pl.events(s, d)).groupBy("gx", F.spark_partition_id().alias("p")).agg(F.min("x").alias("xa"), F.max("x").alias("xb"), F.min("y").alias("ya"), F.max("y").alias("yb"))
    ends = part.select("gx", F.explode(F.array(F.struct(col("xa").alias("x"), col("ya").alias("y")), F.struct(col("xb").alias("x"), col("yb").alias("y")))).alias("e")).select("gx", "e.x", "e.y")
    return ends.groupBy("gx").applyInPandas(box, "gx long, x1 double, y1 double, x2 double, y2 double")


@query("map_in_arrow_local_join", f"SELECT q.qid, d.pid FROM {_QA} q JOIN {E} d ON {_IN}")
def _(s, d):
    from skewtile.operators.baselines import allparts_range

    return allparts_range(qa(s, d), TiledTable.build(pl.events(s, d), 4), "inl_quadtree")


@query("udaf_mbr", f"SELECT event_type, max(x) - min(x) AS wide FROM {E} GROUP BY event_type")
def _(s, d):
    @F.pandas_udf("double")
    def wide(x: pd.Series) -> float:
        return float(x.max() - x.min())

    return ev(s, d).groupBy("event_type").agg(wide("x").alias("wide"))


@query("udtf_quad_cover", f"SELECT qid, gx, gy FROM (SELECT qid, y1, y2, unnest(generate_series(CAST(floor(x1 / 40000e0) AS BIGINT), CAST(floor(x2 / 40000e0) AS BIGINT))) AS gx FROM {_QA}), LATERAL (SELECT unnest(generate_series(CAST(floor(y1 / 40000e0) AS BIGINT), CAST(floor(y2 / 40000e0) AS BIGINT))) AS gy)")
def _(s, d):
    sqlsurface.register(s)
    qa(s, d).createOrReplaceTempView("windows_a")
    return s.sql("SELECT qid, c.gx, c.gy FROM windows_a, LATERAL quad_cover(x1, y1, x2, y2, CAST(40000 AS DOUBLE)) c")


@query("sql_range_join", f"SELECT q.qid, d.pid FROM {_QA} q JOIN {E} d ON {_IN}")
def _(s, d):
    sqlsurface.register(s)
    return sqlsurface.range_join(s, qa(s, d), TiledTable.build(pl.events(s, d), 8))


@query("sql_knn", "SELECT qid, pid, rank FROM (SELECT q.pid AS qid, d.pid, row_number() OVER (PARTITION BY q.pid ORDER BY (d.x - q.x) * (d.x - q.x) + (d.y - q.y) * (d.y - q.y), d.pid, d.x, d.y) AS rank FROM " + E + " q, " + E + " d WHERE q.pid % 100 = 0) WHERE rank <= 5")
def _(s, d):
    sqlsurface.register(s)
    e = pl.events(s, d)
    return sqlsurface.knn(s, pl.focal_points(e, 100), TiledTable.build(e, 8), 5)
