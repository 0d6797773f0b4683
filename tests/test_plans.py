"""Cost model, planner, tile maps, filters and kernels: worked examples, invariants, brute force."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from skewtile.functions import curves
from skewtile.functions import geometry as g
from skewtile.operators import baselines, local
from skewtile.plans import obf, planner
from skewtile.plans.cost import CostModel, Tile, calibrate
from skewtile.plans.tilemap import TileMap

PARTS = {"hot": [("h1", Tile(22, 12)), ("h2", Tile(28, 18))], "warm": [("w1", Tile(25, 10)), ("w2", Tile(25, 10))]}
TILES = [("hot", Tile(50, 30)), ("warm", Tile(50, 20)), *((f"c{i}", Tile(50, 10)) for i in range(3))]


def cut(h, k):
    return PARTS.get(h, []) if k == 2 else []


def test_cost_of_the_worked_example():
    m = CostModel()
    assert m.plan([t for _, t in TILES]) == pytest.approx(340)
    assert m.split(Tile(50, 30), [Tile(22, 12), Tile(28, 18)]) == pytest.approx(117.36)
    assert m.plan_after([t for _, t in TILES], 0, [Tile(22, 12), Tile(28, 18)]) == pytest.approx(225)


def test_planner_trail_of_the_worked_example():
    plan = planner.greedy(TILES, cut, 5)
    assert plan.costs == pytest.approx([340, 225, 132.36])
    assert plan.spare == [5, 3, 1] and plan.n_tiles == 7
    assert set(plan.splits) == {"hot", "warm"}


@pytest.mark.parametrize("rule", ["plan", "tile"])
@pytest.mark.parametrize("accounting, budget", [("children", 5), ("net", 4), ("total", 8)])
def test_planner_never_raises_the_cost(rule, accounting, budget):
    plan = planner.greedy(TILES, cut, budget, accept_rule=rule, accounting=accounting)
    assert all(b < a for a, b in zip(plan.costs, plan.costs[1:])) and min(plan.spare) >= 0


def test_planner_against_all_plans():
    hist = [planner.Histogram((0, 0, 8, 8), np.full((8, 8), n), np.full((8, 8), q)) for n, q in ((4, 3), (4, 1), (2, 1))]
    tiles = [(h, h.tile()) for h in hist]
    made = planner.cutter("query")
    assert planner.greedy(tiles, made, 4).cost >= planner.brute_force(tiles, made, 4) - 1e-9


def test_cuts_balance_what_they_are_asked_to():
    data, query = np.ones((16, 16)), np.zeros((16, 16))
    query[:2, :2] = 10
    h = planner.Histogram((0, 0, 16, 16), data, query)
    for by, of in (("query", "query"), ("data", "data")):
        parts = planner.leaves(h.cut(4, by))
        w = [getattr(p, of).sum() for p in parts]
        assert len(parts) == 4 and max(w) <= 2 * np.mean(w)
    tree = planner.graft(h, parts)
    assert tree is not None


def test_classify_drift_and_calibration():
    assert planner.classify([Tile(50, 50), Tile(50, 1), Tile(50, 1)], CostModel()) == [True, False, False]
    assert planner.should_replan([10, 10, 10], [40, 1, 1]) and not planner.should_replan([10, 10], [11, 9])
    assert calibrate([(Tile(10, 10), 5.0), (Tile(20, 10), 10.0)]).p_local == pytest.approx(0.05)


@pytest.mark.parametrize("kind", ["kd", "str_pack", "quadtree"])
@given(st.lists(st.tuples(st.integers(-50, 50), st.integers(-50, 50)), min_size=1, max_size=200), st.integers(1, 20))
@settings(max_examples=30, deadline=None)
def test_every_point_has_one_tile(kind, pts, n):
    p = np.array(pts, float)
    tm = getattr(TileMap, kind)(p, n)
    box = tm.boxes()
    q = np.vstack([p, p + 0.5, [[1e9, -1e9]]])
    t = tm.locate(q[:, 0], q[:, 1])
    inside = (q[:, None, 0] >= box[:, 0]) & (q[:, None, 0] < box[:, 2]) & (q[:, None, 1] >= box[:, 1]) & (q[:, None, 1] < box[:, 3])
    assert (inside.sum(1) == 1).all() and (inside.argmax(1) == t).all()
    assert TileMap.from_json(tm.to_json()).boxes().tolist() == box.tolist()


def test_grid_and_split():
    tm = TileMap.grid((0, 0, 4, 4), 2, 2)
    assert tm.n_tiles == 4
    new, names = tm.split({0: (0, 1.0, None, None)})
    assert new.n_tiles == 5 and len(names[0]) == 2


# filters ----------------------------------------------------------------------------------------

EXAMPLE = [[True, False, True, False], True, [False, [True, False, False, True], True, False], [True, False, [True, False, True, False], True]]


def test_filter_encoding_of_the_worked_example():
    f = obf.encode(EXAMPLE, (0, 0, 1, 1))
    assert f.internal.astype(int).reshape(-1, 4).tolist()[:2] == [[1, 0, 1, 1], [0, 0, 0, 0]]
    assert (len(f.internal), int(f.internal.sum()), len(f.leaf), f.size_bits) == (24, 5, 19, 43)
    assert obf.child(f, 0) == ("internal", 4) and obf.child(f, 14) == ("internal", 20)
    assert obf.decode(f) == EXAMPLE
    for at in range(24):
        assert len({obf.rank_ones(f, at, m) for m in ("scan", "level", "table")}) == 1


def complete(depth):
    return True if depth == 1 else [complete(depth - 1)] * 4


@pytest.mark.parametrize("depth, bits", [(1, 1), (2, 8), (3, 36)])
def test_space_of_complete_trees(depth, bits):
    assert obf.encode(complete(depth), (0, 0, 1, 1)).size_bits == bits


@pytest.fixture(scope="module")
def crowd():
    rng = np.random.default_rng(3)
    x, y = np.round(rng.exponential(150, 1500)) % 1000, np.round(rng.exponential(90, 1500)) % 1000
    low = np.round(rng.random((300, 2)) * 1000)
    rects = np.column_stack([low, low + 25])
    truth = np.array([((x >= a) & (x <= c) & (y >= b) & (y <= d)).any() for a, b, c, d in rects])
    return x, y, rects, truth


def test_filter_is_sound_in_every_version(crowd):
    x, y, rects, truth = crowd
    f = obf.build(x, y, (float(x.min()), float(y.min()), float(x.max()), float(y.max())))
    said = obf.may_contain_batch(f, rects)
    assert f.size_bits == 7 * f.n_internal + 1 and not (truth & ~said).any()
    assert said.tolist() == [obf.may_contain(f, tuple(r)) for r in rects]
    false = (said & ~truth).sum()
    learned = {b: f for b in ("keep", "exact")}
    for b in learned:
        for r in rects[~truth]:
            learned[b] = obf.mark_empty(learned[b], tuple(r), b, 9, (x, y))
        again = obf.may_contain_batch(learned[b], rects)
        assert not (truth & ~again).any()
        assert (again & ~truth).sum() <= false
    assert (obf.may_contain_batch(learned["exact"], rects) & ~truth).sum() < false / 2
    small = obf.shrink(learned["exact"], 2000)
    said = obf.may_contain_batch(small, rects)
    assert small.size_bits <= 2000 and not (truth & ~said).any()
    for policy in ("lru", "mru"):
        assert obf.shrink(f, 700, policy, {(0,): 3}).size_bits <= 700
    both = obf.merge(f, learned["exact"])
    assert not (truth & ~obf.may_contain_batch(both, rects)).any()
    grown = obf.add_points(both, np.array([x.max()]), np.array([y.max()]))
    assert obf.may_contain(grown, (float(x.max()), float(y.max()), float(x.max()), float(y.max())))
    with pytest.raises(ValueError):
        obf.merge(f, grown)
    back = obf.Filter.unpack(f.box, *f.pack(), f.n_internal)
    assert (back.internal == f.internal).all() and (back.leaf == f.leaf).all() and back.levels == f.levels


@pytest.mark.parametrize("border", ["exact", "keep"])
@pytest.mark.parametrize("max_depth", [2, 6, 9, 12])
def test_a_batch_of_empty_places_is_learned_in_one_pass(crowd, border, max_depth, monkeypatch):
    """The filter is the one that learns from them one by one, whatever the border, and is read once, not once a place."""
    x, y, rects, truth = crowd
    box = (float(x.min()), float(y.min()), float(x.max()), float(y.max()))
    small, wide = rects[~truth][:40], np.array([[*box[:2], box[0] - 1, box[3]], [box[2], box[3], box[2] + 9, box[3] + 9], [-50, -50, box[0] - 1, 9999]])
    aligned = np.array([obf.quadrant(obf.quadrant(obf.quadrant(box, 1), 2), 0)])
    for f, probes in ((obf.build(x, y, box), np.vstack([small, wide, aligned])), (obf.build(x[:9], y[:9], box, 2), rects[:30]), (obf.build(x[:1] * 0, y[:1] * 0, (0, 0, 0, 0)), rects[:5]), (obf.build(x, y * 0, (*box[:1], 0, box[2], 0)), small)):
        one = f
        for r in probes:
            one = obf.mark_empty(one, tuple(r), border, max_depth, (x, y))
        read, decode = [], obf.decode
        with monkeypatch.context() as m:
            m.setattr(obf, "decode", lambda g: read.append(1) or decode(g))
            got = obf.mark_all_empty(f, probes, border, max_depth, (x, y))
        assert (got.internal == one.internal).all() and (got.leaf == one.leaf).all() and got.levels == one.levels
        assert (got.box, got.version, got.data_version) == (one.box, one.version, one.data_version)
        assert len(read) == 1 or len(f.levels) > max_depth or max_depth > obf.GRID_DEPTH


def test_filter_of_discs_and_of_nothing(crowd):
    x, y, _, _ = crowd
    f = obf.build(x, y, (float(x.min()), float(y.min()), float(x.max()), float(y.max())))
    rng = np.random.default_rng(8)
    discs = np.column_stack([rng.random((200, 2)) * 1000, np.full(200, 20.0)])
    truth = np.array([((x - a) ** 2 + (y - b) ** 2 <= r * r).any() for a, b, r in discs])
    assert not (truth & ~obf.may_contain_batch(f, discs)).any()
    none = obf.build(np.zeros(0), np.zeros(0), (0, 0, 1, 1))
    assert none.size_bits == 1 and not obf.may_contain(none, (0, 0, 1, 1))


def test_shrink_step_of_the_worked_example():
    f = obf.encode(EXAMPLE, (0, 0, 1, 1))
    once = obf.shrink(f, f.size_bits - 7, prefer_lossless=False)
    assert once.size_bits == f.size_bits - 7 and obf.decode(once) != EXAMPLE


@pytest.mark.parametrize("kind", ["obf", "obf_adaptive", "rtree", "quadtree", "bloom"])
def test_index_probe(crowd, kind):
    x, y, rects, _ = crowd
    r = baselines.index_probe(kind, x, y, rects)
    assert r["false_negatives"] == 0
    if kind.startswith("obf"):
        assert r["mb"] < baselines.index_probe("rtree", x, y, rects)["mb"]


# kernels ----------------------------------------------------------------------------------------

SHAPES = {
    "crowd": lambda r: (np.round(r.exponential(100, 800)), np.round(r.exponential(100, 800))),
    "line": lambda r: (np.round(r.random(300) * 1000), np.zeros(300)),
    "one place": lambda r: (np.full(200, 5.0), np.full(200, 5.0)),
    "one point": lambda r: (np.array([3.0]), np.array([4.0])),
}


@pytest.mark.parametrize("shape", SHAPES)
@pytest.mark.parametrize("algo", [a for a in local.RANGE if a != "brute"])
def test_range_kernels(shape, algo):
    x, y = SHAPES[shape](np.random.default_rng(1))
    mid = np.column_stack([x, y])[:120]
    rects = np.vstack([np.column_stack([mid - 7, mid + 7]), np.column_stack([mid[:1], mid[:1]]), [[-1e9, -1e9, 1e9, 1e9]], [[1e8, 1e8, 1e9, 1e9]]])
    want = set(zip(*(c.tolist() for c in local.range_brute(x, y, rects))))
    q, i = local.RANGE[algo](x, y, rects)
    assert len(q) == len(want) and set(zip(q.tolist(), i.tolist())) == want


@pytest.mark.parametrize("shape", SHAPES)
@pytest.mark.parametrize("algo", [a for a in local.KNN if a != "brute"])
def test_knn_kernels(shape, algo):
    x, y = SHAPES[shape](np.random.default_rng(2))
    pid = np.arange(len(x))[::-1].copy()
    qx, qy = x[:60] + 1, y[:60]
    for k, bound in ((1, None), (10, None), (5, np.full(len(qx), 400.0))):
        want = sorted(zip(*(c.tolist() for c in (lambda q, i, d: (q, pid[i], d))(*local.knn("brute", pid, x, y, qx, qy, k, bound)))))
        q, i, d = local.knn(algo, pid, x, y, qx, qy, k, bound)
        assert sorted(zip(q.tolist(), pid[i].tolist(), d.tolist())) == want


def test_local_planner():
    assert local.choose("polygon", 10, 10) == "dual_tree"
    assert local.choose("point", 10**6, 10**4) == "inl_quadtree" and local.choose("point", 10, 10) == "brute"


# functions --------------------------------------------------------------------------------------


def test_curves():
    x, y = np.meshgrid(np.arange(16), np.arange(16))
    x, y = x.ravel(), y.ravel()
    assert all((a == b).all() for a, b in zip(curves.unmorton(curves.morton(x, y)), (x, y)))
    h = curves.hilbert(x, y, 4)
    order = np.argsort(h)
    assert sorted(h) == list(range(256))
    assert (abs(np.diff(x[order])) + abs(np.diff(y[order])) == 1).all()


def test_shape_predicates():
    square, cross, far = [(0, 0), (4, 0), (4, 4), (0, 4)], [(-1, 2), (5, 2)], [(9, 9), (10, 10)]
    assert g.shapes_intersect("polygon", square, "polyline", cross) and not g.shapes_intersect("polygon", square, "polyline", far)
    assert g.shapes_intersect("polygon", square, "point", [(2, 2)]) and g.shapes_intersect("polygon", square, "point", [(4, 4)])
    assert g.shape_contains("polygon", square, "segment", [(1, 1), (2, 2)]) and not g.shape_contains("polygon", square, "polyline", cross)
    assert g.shapes_within("segment", [(0, 0), (1, 0)], "segment", [(0, 2), (1, 2)], 2.0) and not g.shapes_within("segment", [(0, 0), (1, 0)], "segment", [(0, 2), (1, 2)], 1.9)


def test_visits_keep_what_queries_use():
    """Shrinking by visits merges what no query visits first; the most visited part keeps its detail, and nothing is lost."""
    rng = np.random.default_rng(12)
    x, y = rng.random(4000) * 100, rng.random(4000) * 100
    x, y = x[(x * 7 % 10 < 5) | (y * 3 % 10 < 4)], y[(x * 7 % 10 < 5) | (y * 3 % 10 < 4)]
    f = obf.build(x, y, (0.0, 0.0, 100.0, 100.0))
    hot = [(a, b, a + 1.0, b + 1.0) for a, b in rng.random((200, 2)) * 20]
    seen = obf.visits(f, hot)
    assert seen[()] == 200 and all(n <= seen[p[:-1]] for p, n in seen.items() if p)
    small = {p: obf.shrink(f, f.size_bits // 3, p, seen, prefer_lossless=False) for p in ("lru", "mru")}
    false = {p: sum(obf.may_contain(s, h) and not ((x >= h[0]) & (x <= h[2]) & (y >= h[1]) & (y <= h[3])).any() for h in hot) for p, s in small.items()}
    assert false["lru"] <= false["mru"]
    for s in small.values():
        assert all(obf.may_contain(s, (a, b, a, b)) for a, b in zip(x[:300], y[:300]))


@pytest.mark.parametrize("algo", sorted(local.RANGE))
def test_range_kernels_answer_in_bounded_pieces(algo, monkeypatch):
    """However many pairs a batch has, a kernel holds a bounded number of them at once; none is lost at the borders."""
    monkeypatch.setattr(local, "_PIECE", 512)
    rng = np.random.default_rng(3)
    x, y = rng.integers(0, 40, 400).astype(float), rng.integers(0, 40, 400).astype(float)
    rects = np.array([[a, b, a + 25, b + 25] for a, b in rng.integers(-5, 30, (60, 2))] + [[-1, -1, 50, 50], [7, 7, 7, 7], [60, 60, 70, 70]], float)
    pieces = list(local.PROBES[algo](x, y)(rects))
    got = [pair for p in pieces for pair in zip(*(c.tolist() for c in p))]
    want = [(q, i) for q, (a, b, c, d) in enumerate(rects) for i in range(400) if a <= x[i] <= c and b <= y[i] <= d]
    assert sorted(got) == want and len(pieces) > 3 and max(len(p[0]) for p in pieces) <= 512 + 400


@pytest.mark.parametrize("algo", ["inl_quadtree", "inl_rtree", "dual_tree"])
def test_blocks_within_a_window_are_not_tested(algo, monkeypatch):
    """Points are tested along a window's border only; no pair is lost or comes twice for it."""
    tested, keep = [], local._keep
    monkeypatch.setattr(local, "_keep", lambda px, py, rects, q, i, order: tested.append(len(q)) or keep(px, py, rects, q, i, order))
    rng = np.random.default_rng(8)
    x, y = rng.integers(0, 1000, 5000).astype(float), rng.integers(0, 1000, 5000).astype(float)
    rects = np.array([[100, 100, 900, 900], [-1, -1, 1000, 1000], [5, 5, 5, 5], [700, 0, 999, 999]], float)
    q, i = (np.concatenate(c) for c in zip(*local.PROBES[algo](x, y)(rects)))
    want = [(q, i) for q, (a, b, c, d) in enumerate(rects) for i in np.flatnonzero((x >= a) & (x <= c) & (y >= b) & (y <= d))]
    assert sorted(zip(q.tolist(), i.tolist())) == want
    assert sum(tested) < len(want) / 2
