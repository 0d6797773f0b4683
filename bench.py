"""Times the headline queries and prints one JSON line. With --study: the local algorithms, the filters and the planner, one JSON line each;
with --scaling: a skewed join at 1, 2, 4 and 8 cores, with and without its plan."""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from skewtile import metrics, workloads
from skewtile.operators import baselines, knnjoin, local, rangejoin, search
from skewtile.operators.tiled import TiledTable
from skewtile.sources import planes
from skewtile.sources.formats import scratch

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def session() -> SparkSession:
    s = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    return s


def run(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def main() -> None:
    """Tables are laid out, indexed and cached once, as for a standing service; queries and joins then run on them. Builds are timed too."""
    spark = session()
    run(workloads.QUERIES["range_join_area_b_opt"](spark, SF_DIR))  # compiles code, forks workers
    took: dict[str, float] = {}

    def time_of(name: str, f, times: int = 1) -> None:
        took[name] = metrics.timed(lambda: [f() for _ in range(times)])[1] / times

    planes_of = {"events": "E", "lineitem": "L"}
    raw = {n: planes.PLANES[p](spark, SF_DIR).persist() for n, p in planes_of.items()}
    for n in raw:
        raw[n].count()
    tables = {}

    def build(n: str, kind: str) -> None:
        tt = TiledTable.build(raw[n], 32, kind, with_filters=True).laid_out(persist=True)
        tt.df.count()
        tables[n, kind] = tt

    for n in raw:
        for kind in ("kd", "quadtree"):
            time_of(f"build_{n}_{kind}", lambda n=n, k=kind: build(n, k))
    box = {"events": (500000.0, 0.0, 800000.0, 200000.0), "lineitem": (2000000.0, 4000000.0, 3000000.0, 5000000.0)}
    for (n, kind), tt in tables.items():
        time_of(f"range_search_{n}_{kind}", lambda tt=tt, n=n: search.range_search(tt, box[n]).count(), 5)
        for k in (10, 30):
            time_of(f"knn_search_k{k}_{n}_{kind}", lambda tt=tt, n=n, k=k: search.knn_search(tt, box[n][0], box[n][1], k).collect(), 3)
    e, lines = tables["events", "kd"], tables["lineitem", "kd"]
    hot, every = (planes.windows_of(raw["events"], 20000.0, m, a).persist() for m, a in ((5, "a"), (50, None)))
    focal = planes.focal_points(raw["events"], 40).persist()
    wide = planes.windows_of(raw["lineitem"], 100000.0, 199).persist()
    spot = hot_spot(raw["lineitem"], lines).persist()
    for q in (hot, every, focal, wide, spot):
        q.count()

    def plans(name: str, q, table: TiledTable) -> None:
        """The first batch of a kind pays for its plan and split; later ones take them."""
        time_of(f"{name}_plan", lambda: [part.count() for part in rangejoin.planned(q, table).more])

    for name, q in (("hot", hot), ("all", every)):
        time_of(f"range_join_{name}", lambda q=q: run(rangejoin.range_join(q, e)))
        plans(f"range_join_{name}", q, e)
        time_of(f"range_join_{name}_opt", lambda q=q: run(rangejoin.range_join(q, e, plan="query", filter=True)))
        time_of(f"range_join_{name}_cartesian", lambda q=q: run(baselines.cartesian_range(q, raw["events"])))
        time_of(f"range_join_{name}_allparts", lambda q=q: run(baselines.allparts_range(q, e)))
        time_of(f"range_join_{name}_tilescan", lambda q=q: run(baselines.tilescan_range(q, e)))
        time_of(f"range_join_{name}_aqe", lambda q=q: run(rangejoin.aqe_join(q, e)))
    time_of("range_join_hot_save", lambda: rangejoin.range_join(hot, e).write.mode("overwrite").parquet(scratch(spark, "saved")))
    for half in (20000.0,):
        time_of("distance_join_datarep", lambda: run(baselines.datarep_distance_join(focal, e, half)))
        time_of("distance_join_datarep_opt", lambda: run(baselines.datarep_distance_join(focal, e, half, opt=True)))
    time_of("range_join_lineitem", lambda: run(rangejoin.range_join(wide, lines)))
    time_of("range_join_lineitem_cartesian", lambda: run(baselines.cartesian_range(wide, raw["lineitem"])))
    plans("hot_spot", spot, lines)
    for local in ("catalyst", "auto"):
        time_of(f"hot_spot_{local}", lambda x=local: run(rangejoin.range_join(spot, lines, local=x)))
        time_of(f"hot_spot_{local}_opt", lambda x=local: run(rangejoin.range_join(spot, lines, local=x, plan="query", filter=True)))
    for k in (50, 100, 150):
        time_of(f"knn_join_k{k}", lambda k=k: run(knnjoin.knn_join(focal, e, k)))
        time_of(f"knn_join_k{k}_opt", lambda k=k: run(knnjoin.knn_join(focal, e, k, plan="query", filter=True)))
    time_of("knn_join_k50_allparts", lambda: run(baselines.allparts_knn(focal, e, 50)))
    time_of("knn_join_k50_pivot", lambda: run(baselines.pivot_knn(focal, raw["events"], 50, stage=scratch(spark, "pivots"))))
    time_of("knn_join_k50_datarep", lambda: run(baselines.datarep_knn(focal, e, 50)))
    at = spot.select("qid", ((F.col("x1") + F.col("x2")) / 2).alias("cx"), ((F.col("y1") + F.col("y2")) / 2).alias("cy")).persist()
    at.count()
    time_of("knn_hot_spot", lambda: run(knnjoin.knn_join(at, lines, 20)))
    time_of("knn_hot_spot_opt_first", lambda: run(knnjoin.knn_join(at, lines, 20, plan="query", filter=True)))
    time_of("knn_hot_spot_opt", lambda: run(knnjoin.knn_join(at, lines, 20, plan="query", filter=True)))
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": {k: round(v, 4) for k, v in took.items()}, "sf": float(SF_DIR.rpartition("sf")[2])}))


def hot_spot(points, table: TiledTable, half: float = 60000.0):
    """Windows around all points of the fullest tile, as when every query of a batch comes from one city."""
    tile = int(table.counts.argmax())
    p = table.df.where(F.col("tile") == tile)
    return p.select(F.col("pid").alias("qid"), (F.col("x") - half).alias("x1"), (F.col("y") - half).alias("y1"), (F.col("x") + half).alias("x2"), (F.col("y") + half).alias("y2"))


def points(spark: SparkSession, plane: str, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    p = planes.PLANES[plane](spark, SF_DIR).select("pid", "x", "y").orderBy("pid").limit(n).toPandas()
    return tuple(p[c].to_numpy() for c in ("pid", "x", "y"))


def study() -> None:
    spark = session()
    for n in (30_000, 120_000, 300_000):
        pid, x, y = points(spark, "L", n)
        mid = np.column_stack([x, y])[:: max(1, n // 3000)]
        rects = np.column_stack([mid - 50_000, mid + 50_000])
        out = {a: round(metrics.timed(lambda f=f: f(x, y, rects))[1], 4) for a, f in local.RANGE.items() if a != "brute"}
        print(json.dumps({"study": "local range join", "points": n, "queries": len(rects), "seconds": out}), flush=True)
    pid, x, y = points(spark, "L", 100_000)
    for k in (10, 50, 150):
        out = {a: round(metrics.timed(lambda a=a: local.knn(a, pid, x, y, x[::200], y[::200], k))[1], 4) for a in local.KNN if a != "brute"}
        print(json.dumps({"study": "local nearest-neighbour join", "k": k, "queries": 500, "seconds": out}), flush=True)
    for plane in ("E", "L"):
        _, x, y = points(spark, plane, 50_000)
        corner = np.random.default_rng(1).random((1000, 2)) * [x.max(), y.max()]
        probes = np.column_stack([corner, corner + [x.max() / 150, y.max() / 150]])
        for kind in ("rtree", "quadtree", "obf", "obf_adaptive", "bloom"):
            print(json.dumps({"study": "filter", "plane": plane, "kind": kind} | {k: round(v, 5) for k, v in baselines.index_probe(kind, x, y, probes).items()}), flush=True)
    for n in (5_000, 20_000, 70_000):
        pid, x, y = points(spark, "L", 300_000)
        rng = np.random.default_rng(3)
        mid = np.column_stack([x, y])[rng.integers(0, len(x), n)]
        rects = np.column_stack([mid - 5_000, mid + 5_000])
        out = {a: round(metrics.timed(lambda f=f: f(x, y, rects))[1], 4) for a, f in local.RANGE.items() if a != "brute"}
        print(json.dumps({"study": "local range join by queries", "points": len(x), "queries": n, "seconds": out}), flush=True)
        if n <= 20_000:
            out = {a: round(metrics.timed(lambda a=a: local.knn(a, pid, x, y, mid[:, 0], mid[:, 1], 10))[1], 4) for a in ("inl_quadtree", "inl_rtree", "hilbert_block")}
            print(json.dumps({"study": "local nearest-neighbour join by queries", "k": 10, "queries": n, "seconds": out}), flush=True)
    for name in ("shuffle_cost_range", "shuffle_cost_knn", "planner_cost_before_after", "filter_adaptive_round2"):
        began = time.perf_counter()
        rows = [r.asDict() for r in workloads.QUERIES[name](spark, SF_DIR).collect()]
        print(json.dumps({"study": name, "rows": rows, "seconds": round(time.perf_counter() - began, 2)}), flush=True)


def scaling(cores: tuple[int, ...] = (1, 2, 4, 8)) -> None:
    """The hot-spot join and its nearest-neighbour join at several numbers of cores, each in its own process."""
    for n in cores:
        out = subprocess.run([sys.executable, __file__, "--scaled"], env=os.environ | {"BENCH_CPUS": str(n)}, capture_output=True, text=True).stdout.strip().splitlines()
        print(out[-1] if out else json.dumps({"study": "scaling", "cores": n, "failed": True}), flush=True)


def scaled() -> None:
    spark = session()
    table = TiledTable.build(planes.lineitem(spark, SF_DIR), 32, with_filters=True, n_slots=8).laid_out(persist=True)
    table.df.count()
    spot = hot_spot(None, table).persist()
    at = spot.select("qid", ((F.col("x1") + F.col("x2")) / 2).alias("cx"), ((F.col("y1") + F.col("y2")) / 2).alias("cy"))
    cut = rangejoin.planned(spot, table)
    [part.count() for part in cut.more]
    took = {}
    for _ in range(2):  # the second time counts
        took["range"] = metrics.timed(lambda: run(rangejoin.range_join(spot, table, local="auto")))[1]
        took["range_opt"] = metrics.timed(lambda: run(rangejoin.range_join(spot, cut, local="auto", filter=True)))[1]
        took["knn"] = metrics.timed(lambda: run(knnjoin.knn_join(at, table, 20)))[1]
        took["knn_opt"] = metrics.timed(lambda: run(knnjoin.knn_join(at, cut, 20, filter=True)))[1]
    slow = {n: metrics.straggler_profile(spot, t, 0.05) for n, t in (("none", table), ("query", cut))}
    print(json.dumps({"study": "scaling", "cores": int(CPUS), "seconds": {k: round(v, 3) for k, v in took.items()}, "stragglers": slow, "speed_up": {k: round(metrics.speed_up(took[k], took[k + "_opt"]), 2) for k in ("range", "knn")}}), flush=True)


if __name__ == "__main__":
    {"--study": study, "--scaling": scaling, "--scaled": scaled}.get(sys.argv[-1], main)()
