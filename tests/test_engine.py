"""Placement, splitting, learning, streaming loops, degenerate data."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from skewtile import metrics
from skewtile.operators import baselines, knnjoin, rangejoin, search, shapes
from skewtile.operators.tiled import TiledTable, slot_keys
from skewtile.plans import route
from skewtile.plans.tilemap import TileMap, bernoulli, reservoir
from skewtile.sources import formats, generator, planes
from skewtile.streaming import streams
from tests.conftest import MEDIUM, SMALL


@pytest.fixture(scope="module")
def points(spark):
    return planes.events(spark, SMALL).persist()


@pytest.fixture(scope="module")
def tiled(points):
    return TiledTable.build(points, 8, with_filters=True)


def pairs(df):
    return sorted(tuple(r) for r in df.select("qid", "pid").collect())


def test_counts_and_boxes(tiled, points):
    assert tiled.n_rows == points.count()
    assert tiled.df.groupBy("pid").count().where("count > 1").count() == 0
    assert metrics.balance(tiled.counts)["max_over_mean"] < 1.5


@pytest.fixture()
def no_broadcast(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges_over_data(plan: str) -> int:
    """Exchanges of the plan above a scan of the laid-out rows: lines of the tree between the scan and the root on its own branch."""
    lines, found = plan.split("\n"), 0
    depth = lambda x: len(x) - len(x.lstrip(" :+-*()0123456789"))
    for i, line in enumerate(lines):
        if "InMemoryTableScan" not in line and "FileScan" not in line or "slot" not in line:
            continue
        at = depth(line)
        for above in reversed(lines[:i]):
            if depth(above) < at:
                at = depth(above)
                if "Join" in above or "CoGroup" in above:
                    break
                found += "Exchange" in above
    return found


def test_layout_is_reused_by_joins(spark, tiled, points, no_broadcast):
    """Range, distance and nearest-neighbour joins over rows that lie by slot exchange the queries only, in memory or bucketed."""
    laid = tiled.laid_out(persist=True)
    placed = laid.df.select("slot", F.spark_partition_id().alias("p")).distinct().groupBy("slot").count()
    assert placed.where("count > 1").count() == 0 and len(slot_keys(spark, 7)) == 7
    spark.sql("DROP TABLE IF EXISTS laid_points")
    path = formats.scratch(spark, "bucketed")
    tiled.save_bucketed("laid_points", path)
    kept = TiledTable.load_bucketed(spark, "laid_points", path)
    q, f = planes.windows_of(points, 20000.0, 20), planes.focal_points(points, 20)
    want, near = pairs(rangejoin.range_join(q, tiled)), sorted(map(tuple, knnjoin.knn_join(f, tiled, 4).collect()))
    for table in (laid, kept):
        joins = [rangejoin.range_join(q, table, filter=True), rangejoin.range_join(q, table, local="auto"), rangejoin.distance_join(f, table, 20000.0), knnjoin.knn_join(f, table, 4)]
        for df in joins:
            assert "slot" in plan_of(df) and exchanges_over_data(plan_of(df)) == 0, plan_of(df)
        assert plan_of(joins[3]).count("FlatMapCoGroups") == 2
        assert pairs(joins[0]) == pairs(joins[1]) == want and sorted(map(tuple, joins[3].collect())) == near
    assert exchanges_over_data(plan_of(rangejoin.range_join(q, laid).groupBy("pid").count())) == 0
    assert kept.filters is not None and kept.counts.tolist() == tiled.counts.tolist()
    spark.sql("DROP TABLE laid_points")
    laid.df.unpersist()


def test_split_of_a_laid_out_table_leaves_the_rest_in_place(spark, no_broadcast):
    e = planes.events(spark, MEDIUM).persist()
    tt = TiledTable.build(e, 8, with_filters=True, n_slots=4).laid_out(persist=True)
    q, f = planes.windows_of(e, 20000.0, 5, "a"), planes.focal_points(e.where("x BETWEEN 600000 AND 900000 AND y <= 300000"), 5)
    cut = rangejoin.planned(q, tt)
    assert len(cut.parts) == 2 and cut.tiles.n_tiles > 8 and sorted(set(cut.lies_in)) == [0, 1]
    assert pairs(rangejoin.range_join(q, cut, filter=True)) == pairs(rangejoin.range_join(q, tt))
    again = rangejoin.planned(planes.windows_of(e, 20000.0, 7, "c"), cut)
    assert pairs(rangejoin.range_join(q, again)) == pairs(rangejoin.range_join(q, tt))
    got = sorted(map(tuple, knnjoin.knn_join(f, tt, 7, plan="query", filter=True).collect()))
    assert got == sorted(map(tuple, knnjoin.knn_join(f, tt, 7).collect()))
    for part in cut.parts:
        assert part.select("slot", F.spark_partition_id().alias("p")).distinct().groupBy("slot").count().where("count > 1").count() == 0


def test_maps_of_many_tiles(spark):
    """Per-tile values are one literal, so a map far beyond the codegen limit routes, lays out, splits and joins."""
    e = planes.events(spark, MEDIUM).persist()
    tt = TiledTable.build(e, 600, with_filters=True).laid_out()
    assert tt.tiles.n_tiles > 300 and metrics.balance(tt.counts)["max_over_mean"] < 4
    q, f = planes.windows_of(e, 20000.0, 200), planes.focal_points(e, 200)
    want = pairs(baselines.cartesian_range(q, e))
    assert pairs(rangejoin.range_join(q, tt, filter=True, plan="query")) == want == pairs(rangejoin.range_join(q, tt, strategy="replicate_inner"))
    assert sorted(map(tuple, knnjoin.knn_join(f, tt, 5, filter=True).collect())) == sorted(map(tuple, baselines.cartesian_knn(f, e, 5).collect()))


def test_distance_joins_are_exact_on_fractions_and_repeated_points(spark):
    rows = [(i % 70, 0.1 * (i % 90), 0.1 * (i // 90)) for i in range(300)] + [(5, 0.3, 0.0)] * 3
    p = spark.createDataFrame(rows, "pid long, x double, y double")
    q = spark.createDataFrame([(i, 0.1 * i, 0.1 * (i % 3)) for i in range(60)], "qid long, cx double, cy double")
    tt = TiledTable.build(p, 5)
    want = pairs(baselines.distance_by_circle(q, p, 0.3))
    for options in ({}, {"local": "auto"}, {"filter": True}, {"plan": "query"}, {"strategy": "replicate_inner"}, {"dedup": True}):
        assert pairs(rangejoin.distance_join(q, tt, 0.3, **options)) == want, options
    hits = {a for a, _ in want}
    assert {r.qid for r in rangejoin.distance_join(q, tt, 0.3, how="anti").collect()} == set(range(60)) - hits


def test_filters_pass_shapes_without_end(spark):
    p = spark.createDataFrame([(i, float(i % 7), float(i // 7)) for i in range(40)], "pid long, x double, y double")
    tt = TiledTable.build(p, 4, with_filters=True)
    q = spark.createDataFrame([(1, 3.0, 3.0), (2, 50.0, -9.0)], "qid long, cx double, cy double")
    for bound in ("home", "counts", "sample"):
        for k in (40, 50):
            assert knnjoin.knn_join(q, tt, k, bound=bound, filter=True).count() == 80, (bound, k)


def test_windows_cut_to_tiles_with_mixed_sizes(spark, points):
    w = points.where("pid % 25 = 0").select(F.col("pid").alias("qid"), "x", "y", F.pow(F.lit(10.0), F.col("pid") % 7).alias("h"))
    w = w.select("qid", (F.col("x") - F.col("h")).alias("x1"), (F.col("y") - F.col("h")).alias("y1"), (F.col("x") + F.col("h")).alias("x2"), (F.col("y") + F.col("h")).alias("y2"))
    tt = TiledTable.build(points, 8)
    cells = rangejoin.Cells.of(w, tt.tiles)
    assert len(cells.levels) <= 6 and pairs(rangejoin.range_join(w, tt)) == pairs(baselines.cartesian_range(w, points))


def test_nearest_neighbours_of_two_tiles(spark):
    """Three nearest of a point near its tile's border: two are at home, the third in the neighbour, which the home radius reaches."""
    rows = [(1, 9.0, 5.0), (2, 8.5, 5.0), (3, 10.5, 5.0), (4, 4.0, 5.0), (5, 1.0, 1.0), (6, 19.0, 5.0), (7, 15.0, 9.0)]
    tt = TiledTable.build(spark.createDataFrame(rows, "pid long, x double, y double"), tile_map=TileMap.grid((0.0, 0.0, 20.0, 10.0), 2, 1))
    q = spark.createDataFrame([(6, 9.5, 5.0)], "qid long, cx double, cy double")
    home = tt.tiles.locate(np.array([9.5]), np.array([5.0]))[0]
    candidates = [r[0] for r in rows if tt.tiles.locate(np.array([r[1]]), np.array([r[2]]))[0] == home]
    assert sorted(candidates) == [1, 2, 4, 5]
    routed = route.circles(q.withColumn("r2", F.lit(5.5**2)), tt.tiles, F.col("r2"))
    assert routed.count() == 2
    assert [r.pid for r in knnjoin.knn_join(q, tt, 3).orderBy("rank").collect()] == [1, 3, 2] or [r.pid for r in knnjoin.knn_join(q, tt, 3).orderBy("rank").collect()] == [1, 2, 3]


def test_sampled_and_calibrated_costs(spark):
    from skewtile.plans.cost import Tile, calibrate_sampled, sampled_local

    e = planes.events(spark, MEDIUM)
    tt, q = TiledTable.build(e, 8), planes.windows_of(e, 20000.0, 20)
    true = {r.tile: r.n for r in rangejoin.tile_times(q, tt).select("tile", F.col("pairs").alias("n")).collect()}
    guess = rangejoin.sampled_pairs(q, tt)
    assert abs(guess.sum() - sum(true.values())) < 0.25 * sum(true.values())
    assert np.corrcoef([guess[t] for t in range(8)], [true.get(t, 0) for t in range(8)])[0, 1] > 0.8
    timed = [(Tile(n, m, p), sampled_local(p, 1, 1, n, m, 2e-6, 3e-8)) for n, m, p in ((1000, 50, 400), (20000, 10, 90000), (5000, 900, 2000), (100, 9000, 800000))]
    model = calibrate_sampled(timed, 1e6)
    assert model.p_probe == pytest.approx(2e-6, rel=1e-3) and model.p_pair == pytest.approx(3e-8, rel=1e-3)
    costs = rangejoin.modelled_costs(planes.windows_of(e, 20000.0, 5, "a"), tt, model=rangejoin.calibrated(q, tt), pairs=rangejoin.sampled_pairs(planes.windows_of(e, 20000.0, 5, "a"), tt))
    assert costs == sorted(costs, reverse=True)


def test_local_planner():
    from skewtile.operators import local

    assert local.choose("shape", 10, 10) == "dual_tree" and local.choose("point", 10, 10) == "brute" and local.choose("point", 10**6, 10) == "inl_quadtree"
    assert [local.choose("point", n, 10**4, quadtree=False) for n in (10**5, 2 * 10**5)] == ["dual_tree", "inl_rtree"]
    assert [local.choose("point", 10**5, n, 10, quadtree=False) for n in (10**4, 10**5)] == ["inl_rtree", "hilbert_block"]


def test_learning_from_nearest_neighbours(spark):
    e = planes.events(spark, SMALL).persist()
    tt = TiledTable.build(e, 4, with_filters=True)
    q = e.where("pid % 20 = 0").select(F.col("pid").alias("qid"), (F.col("x") + 37000).alias("cx"), (F.col("y") + 410000).alias("cy"))
    learned = knnjoin.adapt(q, tt)
    w = q.select("qid", (F.col("cx") - 3000).alias("x1"), (F.col("cy") - 3000).alias("y1"), (F.col("cx") + 3000).alias("x2"), (F.col("cy") + 3000).alias("y2"))
    assert metrics.routed_records(w, learned, True) < metrics.routed_records(w, tt, True)
    assert pairs(rangejoin.range_join(w, learned, filter=True)) == pairs(baselines.cartesian_range(w, e))


def test_skew_join_of_spark_is_planned(spark, no_broadcast):
    """What Spark does about skew by itself: a large partition of a sort-merge join is read in pieces."""
    settings = {"spark.sql.adaptive.skewJoin.skewedPartitionThresholdInBytes": "20KB", "spark.sql.adaptive.skewJoin.skewedPartitionFactor": "2", "spark.sql.adaptive.advisoryPartitionSizeInBytes": "20KB", "spark.sql.adaptive.coalescePartitions.enabled": "false", "spark.sql.shuffle.partitions": "6"}
    for k, v in settings.items():
        spark.conf.set(k, v)
    try:
        e = planes.events(spark, MEDIUM).where("x < 400000 OR pid % 10 = 0").repartition(12, "pid")
        tt = TiledTable.build(e, tile_map=TileMap.grid((0.0, 0.0, 2600000.0, 2600000.0), 4, 1))
        q = planes.windows_of(e, 2000.0, 40)
        df = rangejoin.aqe_join(q, tt)
        want = pairs(baselines.cartesian_range(q, e))
        got = sorted(tuple(r) for r in df.collect())
        assert got == want and "skew=true" in plan_of(df)
    finally:
        for k in settings:
            spark.conf.unset(k)
        spark.conf.set("spark.sql.shuffle.partitions", "8")


def test_sort_aggregate_and_range_partitioned_sort(spark, points):
    text = points.select((F.col("pid") % 9).alias("k"), F.col("pid").cast("string").alias("s"))
    spark.conf.set("spark.sql.execution.useObjectHashAggregateExec", "false")
    try:
        df = text.groupBy("k").agg(F.max("s").alias("s"))
        assert "SortAggregate" in plan_of(df)
        want = {}
        for r in text.collect():
            want[r.k] = max(want.get(r.k, ""), r.s)
        assert {r.k: r.s for r in df.collect()} == want
    finally:
        spark.conf.unset("spark.sql.execution.useObjectHashAggregateExec")
    ordered = points.repartitionByRange(5, "x").sortWithinPartitions("x", "pid").withColumn("p", F.spark_partition_id())
    ends = ordered.groupBy("p").agg(F.min("x").alias("a"), F.max("x").alias("b")).orderBy("p").collect()
    assert "rangepartitioning" in plan_of(ordered) and all(u.b <= v.a for u, v in zip(ends, ends[1:])) and len(ends) > 2


def test_stream_restarts_where_it_stopped(spark, points):
    folder, log, out = (formats.scratch(spark, n) for n in ("in", "log", "out"))
    for part in (0, 1):
        points.where(F.col("pid") % 2 == part).select("pid", "x").coalesce(1).write.mode("append").parquet(folder)
        stream = spark.readStream.schema("pid long, x double").parquet(folder)
        stream.writeStream.format("parquet").option("checkpointLocation", log).option("path", out).trigger(availableNow=True).start().awaitTermination()
        assert spark.read.parquet(out).count() == points.where(F.col("pid") % 2 <= part).count()
    stream.writeStream.format("parquet").option("checkpointLocation", log).option("path", out).trigger(processingTime="1 second").start().stop()
    assert sorted(r.pid for r in spark.read.parquet(out).collect()) == sorted(r.pid for r in points.collect())


def test_rows_behind_the_watermark_are_dropped(spark):
    assert {(str(r.start), r.n) for r in streams.late_example(spark).collect()} == {("2024-01-01 00:00:00", 2), ("2024-01-01 05:00:00", 1), ("2024-01-01 06:00:00", 2)}


def test_save_and_load(spark, tiled):
    path = formats.scratch(spark, "table")
    tiled.save(path)
    back = TiledTable.load(spark, path)
    assert back.counts.tolist() == tiled.counts.tolist() and back.slots == tiled.slots and "slot" in back.df.columns
    assert {t: f.pack() for t, f in back.filters.filters.items()} == {t: f.pack() for t, f in tiled.filters.filters.items()}
    box = (500000.0, 0.0, 800000.0, 200000.0)
    assert sorted(r.pid for r in search.range_search(back, box).collect()) == sorted(r.pid for r in search.range_search(tiled, box).collect())


def test_split_moves_only_skewed_tiles(spark):
    e = planes.events(spark, MEDIUM)
    tt = TiledTable.build(e, 8)
    q = planes.windows_of(e, 20000.0, 5, "a")
    plan = tt.plan(route.ranges(q, tt.tiles), 6)
    assert plan.splits and plan.costs[-1] < plan.costs[0]
    cut = tt.apply(plan)
    stay, moved = cut.parts
    assert cut.n_rows == tt.n_rows == stay.count() + moved.count()
    assert moved.count() == sum(tt.counts[t] for t in plan.splits)
    assert tt.apply(plan) is cut


def test_learning_lowers_routed_rows_and_loses_nothing(spark):
    e = planes.events(spark, SMALL)
    tt = TiledTable.build(e, 4, with_filters=True)
    q = planes.windows_of(e.withColumn("y", F.col("y") + 400000), 15000.0, 10)
    want = pairs(baselines.cartesian_range(q, e))
    learned = rangejoin.adapt(q, tt)
    assert pairs(rangejoin.range_join(q, learned, filter=True)) == want
    before, after = metrics.routed_records(q, tt, True), metrics.routed_records(q, learned, True)
    assert after <= before <= metrics.routed_records(q, tt, False)
    assert learned.filters.version == 1 and tt.filters.version == 0


def test_streaming_loop_equals_batch(spark, tiled, points):
    q = planes.windows_of(points, 20000.0, 20)
    folder = formats.scratch(spark, "queries")
    q.repartition(2).write.parquet(folder)
    got = []
    loop = streams.BatchLoop(tiled, lambda df, n: got.extend(pairs(df)))
    streams.run_loop(streams.query_files(spark, folder), loop)
    assert sorted(got) == pairs(baselines.cartesian_range(q, points))
    assert loop.table.filters.version >= 1


EMPTY = "qid long, x1 double, y1 double, x2 double, y2 double"


def test_nothing_on_either_side(spark, tiled, points):
    none = spark.createDataFrame([], EMPTY)
    assert rangejoin.range_join(none, tiled).count() == 0
    assert knnjoin.knn_join(spark.createDataFrame([], "qid long, cx double, cy double"), tiled, 3).count() == 0
    bare = TiledTable.build(points.limit(0), 4)
    q = planes.windows_of(points, 1000.0, 100)
    assert rangejoin.range_join(q, bare).count() == 0
    assert knnjoin.knn_join(planes.focal_points(points, 100), bare, 3, bound="counts").count() == 0


ROWS = [(1, 0.0, 0.0), (2, 0.0, 0.0), (3, 0.0, 0.0), (4, 10.0, 0.0), (5, None, 1.0), (6, float("nan"), 1.0), (7, 10.0, 10.0)]


@pytest.mark.parametrize("bound", ["home", "counts", "sample"])
def test_ties_nulls_and_large_k(spark, bound):
    tt = TiledTable.build(spark.createDataFrame(ROWS, "pid long, x double, y double"), 3)
    assert tt.n_rows == 5
    q = spark.createDataFrame([(1, 0.0, 0.0), (2, 100.0, 100.0)], "qid long, cx double, cy double")
    got = {(r.qid, r.rank): r.pid for r in knnjoin.knn_join(q, tt, 9, bound=bound).collect()}
    assert [got[1, i] for i in range(1, 6)] == [1, 2, 3, 4, 7] and (1, 6) not in got
    assert got[2, 1] == 7
    assert knnjoin.knn_join(q, tt, 0, bound=bound).count() == 0


def test_windows_of_no_area_and_of_everything(spark):
    tt = TiledTable.build(spark.createDataFrame(ROWS, "pid long, x double, y double"), 3, with_filters=True)
    q = spark.createDataFrame([(1, 0.0, 0.0, 0.0, 0.0), (2, -1e9, -1e9, 1e9, 1e9), (3, 50.0, 50.0, 60.0, 60.0), (4, 5.0, 0.0, 1.0, 0.0)], EMPTY)
    for options in ({}, {"filter": True}, {"local": "auto"}, {"dedup": True}):
        assert pairs(rangejoin.range_join(q, tt, **options)) == [(1, 1), (1, 2), (1, 3), (2, 1), (2, 2), (2, 3), (2, 4), (2, 7)]


def test_salted_join(tiled, points):
    q = planes.windows_of(points, 20000.0, 20)
    assert pairs(rangejoin.salted_join(q, tiled, 3)) == pairs(baselines.cartesian_range(q, points))


def test_samples(points):
    assert reservoir(points, 50).count() == 50
    assert 300 < bernoulli(points, 0.5).count() < 700


def test_generator_is_the_same_for_any_partitions(spark):
    a, b = (sorted(map(tuple, generator.generated(spark, n=100, hot=0.3, partitions=p).collect())) for p in (1, 5))
    assert a == b and len(a) == 100


def test_shape_join_against_brute_force(spark):
    e = planes.events(spark, SMALL, "user_id", "ts").where("user_id % 5 = 0")
    lines = shapes.paths(e)
    box = spark.createDataFrame([(i, 400000.0 * i, 0.0, 400000.0 * i + 50000, 400000.0) for i in range(6)], "sid long, x1 double, y1 double, x2 double, y2 double")
    rects = box.select(*shapes.rect_shape(*(F.col(c) for c in ("sid", "x1", "y1", "x2", "y2"))))
    from skewtile.functions import geometry as g

    a, b = lines.collect(), rects.collect()
    pt = lambda s: [(p.x, p.y) for p in s.pts]
    want = sorted((p.sid, q.sid) for p in a for q in b if g.shapes_intersect(p.kind, pt(p), q.kind, pt(q)))
    assert sorted(map(tuple, shapes.shape_join(lines, rects, cell=300000.0).collect())) == want
    near = sorted((p.sid, q.sid) for p in a for q in b if g.shapes_within(p.kind, pt(p), q.kind, pt(q), 30000.0))
    assert sorted(map(tuple, shapes.shape_join(lines, rects, "within_distance", 30000.0, cell=300000.0).collect())) == near


def test_joins_are_observed_as_they_run(tiled, points):
    df, seen = metrics.observed(rangejoin.range_join(planes.windows_of(points, 20000.0, 20), tiled))
    n = len(df.collect())
    assert seen.get["rows"] == n and seen.get["queries"] > 0


def test_joins_written_in_sql_do_not_depend_on_the_map(spark, points):
    from skewtile import sqlsurface

    q, f = planes.windows_of(points, 20000.0, 20), planes.focal_points(points, 50)
    for n in (5, 90):
        tt = TiledTable.build(points, n)
        assert pairs(sqlsurface.range_join(spark, q, tt)) == pairs(baselines.cartesian_range(q, points))
        got = sorted(tuple(r) for r in sqlsurface.knn(spark, f, tt, 3).collect())
        assert got == sorted((r.qid, r.pid, r.rank) for r in baselines.cartesian_knn(f, points, 3).collect())


def test_measures():
    assert metrics.speed_up(10, 2) == 5
    assert metrics.stragglers(np.array([1, 1, 1, 9.0]), 2)["share_under"] == 0.75
    assert metrics.balance(np.array([5, 5, 5]))["gini"] == 0


@pytest.mark.parametrize("local", ["dual_tree"])
def test_kernel_joins_meet_once_in_bounded_blocks(spark, tiled, points, local, monkeypatch):
    """Tiles of many parts and shares give each pair once, for windows, discs and timed joins alike."""
    from skewtile.operators import blocks

    q, f = planes.windows_of(points, 20000.0, 20), planes.focal_points(points, 20)
    want, near = pairs(rangejoin.range_join(q, tiled)), pairs(rangejoin.distance_join(f, tiled, 20000.0))
    monkeypatch.setattr(blocks, "PART_ROWS", 40)
    monkeypatch.setattr(blocks, "SHARE_QUERIES", 20)
    assert pairs(rangejoin.range_join(q, tiled, local=local)) == want
    assert pairs(rangejoin.distance_join(f, tiled, 20000.0, local=local)) == near
    times = rangejoin.tile_times(q, tiled, local).collect()
    assert sum(r.pairs for r in times) == len(want) and {r.tile: r.n_data for r in times}.items() <= dict(enumerate(tiled.counts.tolist())).items()


def test_all_parts_are_asked_in_bounded_pieces(spark, tiled, points, monkeypatch):
    monkeypatch.setattr(baselines, "QUERIES_AT_ONCE", 7)
    q = planes.windows_of(points, 20000.0, 20)
    assert pairs(baselines.allparts_range(q, tiled, "inl_quadtree")) == pairs(rangejoin.range_join(q, tiled))
    assert "InPandas" not in plan_of(baselines.allparts_range(q, tiled))


def test_theta_joins_do_not_nest_loops(spark):
    """Baselines without an index and the plain theta join don't hold every window against every point."""
    from __spark_entry__ import queries

    for name in ("baseline_cartesian_range", "baseline_cartesian_knn", "join_window_theta", "baseline_tilescan_range"):
        plan = plan_of(queries()[name](spark, SMALL))
        assert "NestedLoop" not in plan and "CartesianProduct" not in plan and "SortMergeJoin [tile" not in plan, name


def test_sweeps_without_index_equal_brute_force():
    from skewtile.operators import local

    rng = np.random.default_rng(5)
    x, y = rng.integers(0, 50, 300).astype(float), rng.integers(0, 50, 300).astype(float)
    pid, qx, qy = rng.permutation(300), rng.uniform(-5, 55, 40), rng.uniform(-5, 55, 40)
    for k in (1, 7, 150, 400):
        want = [c.tolist() for c in local.knn_brute(pid, x, y, qx, qy, k)]
        for algo in ("sweep", "inl_quadtree", "inl_rtree", "inl_grid"):
            assert [c.tolist() for c in local.knn(algo, pid, x, y, qx, qy, k)] == want, (algo, k)


def test_cell_counts_bound_nearest_neighbours(spark, tiled, points):
    """The bound holds k points, and is far below what whole tiles give."""
    f = planes.focal_points(points, 20)
    rows = knnjoin.cell_bound(f, tiled, F.lit(3)).collect()
    at = points.select("x", "y").toPandas().to_numpy(float)
    wide = route.bound_from_counts(F.col("cx"), F.col("cy"), tiled.tiles, tiled.counts, F.lit(3))
    far = {r.qid: r.r for r in f.select("qid", wide.alias("r")).collect()}
    for r in rows:
        if r.cell_r2 is not None:
            assert (((at - [r.cx, r.cy]) ** 2).sum(1) <= r.cell_r2).sum() >= 3
    assert np.median([r.cell_r2 / far[r.qid] for r in rows if r.cell_r2 is not None]) < 0.5


def test_sql_joins_meet_in_cells(spark, tiled, points):
    from skewtile import sqlsurface

    for df in (sqlsurface.range_join(spark, planes.windows_of(points, 20000.0, 20), tiled), sqlsurface.knn(spark, planes.focal_points(points, 20), tiled, 3), knnjoin.knn_join(planes.focal_points(points, 20), tiled, 3, bound="counts", local="catalyst")):
        assert "_cx" in plan_of(df)


@pytest.mark.parametrize("exact", [False, True])
def test_shape_trees_stream_bounded_blocks(spark, exact, monkeypatch):
    from skewtile.operators import blocks
    from skewtile.workloads import _order_boxes

    monkeypatch.setattr(blocks, "PART_ROWS", 40)
    a, b = _order_boxes(spark, SMALL, 97), _order_boxes(spark, SMALL, 11)
    tm = TileMap.grid((0.0, 0.0, 1e7, 1.2e7), 2, 2)
    got = shapes.tile_shape_join(a, b, tm, exact=exact, local="auto")
    assert "InPandas" not in plan_of(got)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, shapes.tile_shape_join(a, b, tm, exact=exact).collect()))


def groups_of(dealt):
    """The rows of each group, as (data, queries)."""
    from collections.abc import Iterator

    import pyarrow as pa

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        second = [v for b in batches for v in b.column("second").to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array([second.count(False)]), pa.array([second.count(True)])], ["d", "q"])

    return [tuple(r) for r in dealt.applyInArrow(run, "d long, q long").collect()]


@pytest.mark.parametrize("bound", ["counts", "sample"])
@pytest.mark.parametrize("layout", ["plain", "laid out", "split"])
def test_neighbours_stream_past_bounded_parts(spark, points, bound, layout, monkeypatch):
    """However large the tiles and k, no task is given more than a part of a tile at once, and candidates leave in bounded pieces."""
    from skewtile.operators import blocks
    from skewtile.operators import local as kernels

    f, tt = planes.focal_points(points, 10), TiledTable.build(points, 4, with_filters=True)
    want = sorted(map(tuple, knnjoin.knn_join(f, tt, 30).collect()))
    tt = tt if layout == "plain" else tt.laid_out()
    monkeypatch.setattr(blocks, "PART_ROWS", 60)
    monkeypatch.setattr(blocks, "SHARE_QUERIES", 20)
    dealt, seen = blocks.dealt, []
    monkeypatch.setattr(blocks, "dealt", lambda *a: seen.append(dealt(*a)) or seen[-1])
    got = knnjoin.knn_join(f, tt, 30, bound=bound, filter=True, plan="query" if layout == "split" else None, budget=3)
    assert sorted(map(tuple, got.collect())) == want and len(want) == 30 * f.count()
    assert max(d for g in seen for d, _ in groups_of(g)) < 110 < max(tt.counts)
    x = np.arange(500.0)
    monkeypatch.setattr(kernels, "_PIECE", 100)
    sizes = [len(q) for _, q, _, _ in kernels.knn_probe("inl_rtree", x.astype(int), x, x, 30)(x[:50], x[:50], np.full(50, np.inf))]
    assert max(sizes) <= 100 and sum(sizes) == 30 * 50


def test_counts_of_cells_keep_candidates_few(spark, points):
    """With boxes and counts alone, not whole tiles are candidates."""
    f, tt = planes.focal_points(points, 10), TiledTable.build(points, 1)
    found = []
    with pytest.MonkeyPatch.context() as m:
        m.setattr(knnjoin.route, "circles", lambda q, tm, r2, *a, own=route.circles: found.append(q.withColumn("r2", r2).select("qid", "r2")) or own(q, tm, r2, *a))
        got = sorted(map(tuple, knnjoin.knn_join(f, tt, 3, bound="counts").collect()))
    assert got == sorted(map(tuple, knnjoin.knn_join(f, tt, 3).collect()))
    held = found[0].alias("q").join(f, "qid").crossJoin(points.select("x", "y")).where("(x - cx) * (x - cx) + (y - cy) * (y - cy) <= r2")
    assert held.count() < 0.2 * f.count() * tt.n_rows


def test_distance_kernel_streams_its_discs(spark, tiled, points, monkeypatch):
    """The exact test is made in the kernel's pieces, and no task holds more than a part of a tile: fractional discs as by cells."""
    from pyspark.sql import functions as F

    from skewtile.operators import blocks

    tenth = points.withColumns({"x": F.col("x") / 10, "y": F.col("y") / 10})
    tt, f, dealt, seen = TiledTable.build(tenth, 4), planes.focal_points(tenth, 20), blocks.dealt, []
    want = pairs(rangejoin.distance_join(f, tt, 2000.3))
    monkeypatch.setattr(blocks, "PART_ROWS", 40)
    monkeypatch.setattr(blocks, "dealt", lambda *a: seen.append(dealt(*a)) or seen[-1])
    assert pairs(rangejoin.distance_join(f, tt, 2000.3, local="auto")) == want and want
    assert max(d for d, _ in groups_of(seen[0])) < 80 < max(tt.counts)


def test_all_parts_index_bounded_parts(spark, tiled, points, monkeypatch):
    """A tile is indexed in parts, however few tiles there are."""
    from functools import partial

    from skewtile.operators import blocks

    q, tt, parts, seen = planes.windows_of(points, 20000.0, 20), TiledTable.build(points, 4), blocks.parts, []
    monkeypatch.setattr(blocks, "parts", lambda *a: seen.append(partial(parts, size=40)(*a)) or seen[-1])
    assert pairs(baselines.allparts_range(q, tt, "inl_quadtree")) == pairs(rangejoin.range_join(q, tiled))
    got = [d for d, _ in groups_of(seen[0])]
    assert max(got) < 80 < max(tt.counts) and sum(got) == tt.n_rows


@pytest.mark.parametrize("local", ["dual_tree", "inl_grid", "inl_quadtree", "inl_rtree", "brute"])
def test_each_kernel_gets_bounded_parts(spark, tiled, points, local, monkeypatch):
    from skewtile.operators import blocks

    q, dealt, seen = planes.windows_of(points, 20000.0, 20), blocks.dealt, []
    want = pairs(rangejoin.range_join(q, tiled))
    monkeypatch.setattr(blocks, "PART_ROWS", 20)
    monkeypatch.setattr(blocks, "dealt", lambda *a: seen.append(dealt(*a)) or seen[-1])
    assert pairs(rangejoin.range_join(q, tiled, local=local)) == want
    assert max(d for d, _ in groups_of(seen[0])) < 50 < max(tiled.counts)
