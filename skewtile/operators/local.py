"""Join kernels inside one tile, on numpy arrays. All give the same answers; they differ in what they prune.

Range kernels take points (x, y) and closed windows and return index pairs (query, point). PROBES has them in two steps: an index
over the points, which then answers windows in pieces of bounded size. Nearest-neighbour kernels
return (query, point, squared distance) of the k first in the order (distance, pid, x, y).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np

from skewtile.functions import curves
from skewtile.functions.geometry import np_box_mindist2, np_mindist2, rects_meet

Pairs = tuple[np.ndarray, np.ndarray]
_BLOCK = 1 << 22
_PIECE = 1 << 18
"""Candidates that a range kernel has in its hands at once, however many a window or a batch of windows has."""
FANOUT = 32


def _expand(q: np.ndarray, low: np.ndarray, high: np.ndarray) -> Pairs:
    """(q, i) for all i in low..high of each entry."""
    n = high - low
    return np.repeat(q, n), np.repeat(low - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())


def _spread(q: np.ndarray, low: np.ndarray, high: np.ndarray) -> Iterator[Pairs]:
    """The same in pieces of at most _PIECE entries, the last of one entry's and the first of the next one's together."""
    n = high - low
    end = np.cumsum(n)
    total = int(end[-1]) if len(end) else 0
    for at in range(0, total, _PIECE):
        upto = min(at + _PIECE, total)
        i, j = np.searchsorted(end, at, "right"), np.searchsorted(end, upto)
        lo, hi = low[i : j + 1].copy(), high[i : j + 1].copy()
        lo[0] += at - (end[i] - n[i])
        hi[-1] -= end[j] - upto
        yield _expand(q[i : j + 1], lo, hi)


def _together(pieces: Iterator[Pairs]) -> Pairs:
    return tuple(np.concatenate(c) for c in zip(_none(), *(p for p in pieces if len(p[0]))))


def _keep(px, py, rects, q, i, order) -> Pairs:
    """px, py: the points in that order, which i counts in."""
    v = px[i]
    near = np.flatnonzero((v >= rects[:, 0][q]) & (v <= rects[:, 2][q]))
    q, i = q[near], i[near]
    v = py[i]
    near = np.flatnonzero((v >= rects[:, 1][q]) & (v <= rects[:, 3][q]))
    return q[near], order[i[near]]


def _read(b: Blocks, px, py, rects, q, leaf) -> Iterator[Pairs]:
    """The pairs of windows and blocks that they meet. Points of blocks within their window need no test."""
    r, box = rects[q], b.boxes[leaf]
    whole = (box[:, 0] >= r[:, 0]) & (box[:, 1] >= r[:, 1]) & (box[:, 2] <= r[:, 2]) & (box[:, 3] <= r[:, 3])
    for some, i in _spread(q[whole], b.start[leaf[whole]], b.start[leaf[whole] + 1]):
        yield some, b.order[i]
    q, leaf = q[~whole], leaf[~whole]
    for some, i in _spread(q, b.start[leaf], b.start[leaf + 1]):
        yield _keep(px, py, rects, some, i, b.order)


def _none() -> Pairs:
    return np.zeros(0, np.int64), np.zeros(0, np.int64)


@dataclass(frozen=True)
class Blocks:
    """Points in an order, cut into blocks with boxes: what every index here is at its leaves."""

    order: np.ndarray
    start: np.ndarray
    boxes: np.ndarray

    @classmethod
    def of(cls, x, y, order, start) -> Blocks:
        """start: block borders, n + 1 entries, no block empty."""
        px, py = x[order], y[order]
        cut = start[:-1]
        boxes = np.column_stack([np.minimum.reduceat(px, cut), np.minimum.reduceat(py, cut), np.maximum.reduceat(px, cut), np.maximum.reduceat(py, cut)])
        return cls(order, start, boxes)


def _chunks(n: int, size: int) -> np.ndarray:
    return np.append(np.arange(0, n, size), n)


def quadtree_blocks(x, y, leaf: int = FANOUT) -> Blocks:
    """Leaves of a bucket quadtree: runs of the Morton order, quartered until they hold at most `leaf` points."""
    g = [curves.to_grid(v, v.min(), v.max(), 1 << 16) for v in (x, y)]
    code = curves.morton(*g)
    order = np.argsort(code, kind="stable")
    code = code[order]
    borders, stack = [], [(0, len(code), 0)]
    while stack:
        a, b, d = stack.pop()
        if b - a <= leaf or d == 16:
            if b > a:
                borders.append(a)
            continue
        shift = 2 * (15 - d)
        cuts = a + np.searchsorted((code[a:b] >> shift) & 3, [1, 2, 3])
        stack += list(zip([a, *cuts], [*cuts, b], [d + 1] * 4))
    return Blocks.of(x, y, order, np.append(np.sort(borders), len(code)))


def rtree_blocks(x, y, leaf: int = FANOUT) -> Blocks:
    """Leaves of a sort-tile-recursive packed R-tree."""
    n = len(x)
    slabs = max(1, int(np.ceil(np.sqrt(np.ceil(n / leaf)))))
    by_x = np.argsort(x, kind="stable")
    parts = [s[np.argsort(y[s], kind="stable")] for s in np.array_split(by_x, slabs) if len(s)]
    start = np.concatenate([off + _chunks(len(p), leaf)[:-1] for off, p in zip(np.cumsum([0] + [len(p) for p in parts]), parts)])
    return Blocks.of(x, y, np.concatenate(parts), np.append(start, n))


def grid_blocks(x, y, leaf: int = FANOUT) -> Blocks:
    """Non-empty cells of a uniform grid."""
    side = max(1, int(np.sqrt(len(x) / leaf)))
    cell = curves.to_grid(x, x.min(), x.max(), side) * side + curves.to_grid(y, y.min(), y.max(), side)
    order = np.argsort(cell, kind="stable")
    edge = np.flatnonzero(np.append(True, cell[order][1:] != cell[order][:-1]))
    return Blocks.of(x, y, order, np.append(edge, len(x)))


def hilbert_blocks(x, y, leaf: int = FANOUT, frame=None) -> Blocks:
    """Runs of the Hilbert order."""
    x1, y1, x2, y2 = frame or (x.min(), y.min(), x.max(), y.max())
    h = curves.hilbert(curves.to_grid(x, x1, x2, 1 << 16), curves.to_grid(y, y1, y2, 1 << 16))
    return Blocks.of(x, y, np.argsort(h, kind="stable"), _chunks(len(x), leaf))


def pca_blocks(x, y, leaf: int = FANOUT) -> Blocks:
    """Cells of a grid along the principal components."""
    p = np.column_stack([x, y]) - [x.mean(), y.mean()]
    u = p @ np.linalg.svd(p.T @ p)[0] if len(x) > 1 else p
    side = max(1, int(np.sqrt(len(x) / leaf)))
    row, col = (curves.to_grid(v, v.min(), v.max(), side) for v in (u[:, 0], u[:, 1]))
    order = np.lexsort((np.where(row % 2, -col, col), row))
    return Blocks.of(x, y, order, _chunks(len(x), leaf))


def pivot_blocks(x, y, n_pivots: int, seed: int = 5, rounds: int = 5) -> Blocks:
    """Clusters around k-means pivots."""
    p = np.column_stack([x, y])
    rng = np.random.default_rng(seed)
    pivots = p[rng.choice(len(p), min(n_pivots, len(p)), replace=False)]
    for _ in range(rounds):
        near = nearest_pivot(p, pivots)
        sums = np.column_stack([np.bincount(near, p[:, k], len(pivots)) for k in (0, 1)])
        count = np.bincount(near, minlength=len(pivots))
        pivots = np.where(count[:, None] > 0, sums / np.maximum(count, 1)[:, None], pivots)
    near = nearest_pivot(p, pivots)
    order = np.argsort(near, kind="stable")
    edge = np.flatnonzero(np.append(True, near[order][1:] != near[order][:-1]))
    return Blocks.of(x, y, order, np.append(edge, len(x)))


def nearest_pivot(p: np.ndarray, pivots: np.ndarray) -> np.ndarray:
    out = np.empty(len(p), np.int64)
    step = max(1, _BLOCK // max(1, len(pivots)))
    for a in range(0, len(p), step):
        d = ((p[a : a + step, None, :] - pivots[None]) ** 2).sum(2)
        out[a : a + step] = d.argmin(1)
    return out


# range joins ------------------------------------------------------------------------------------


@dataclass(frozen=True)
class PackedTree:
    """Boxes of blocks, and above them boxes of FANOUT neighbours each, up to one root."""

    levels: list[np.ndarray]

    @classmethod
    def over(cls, boxes: np.ndarray) -> PackedTree:
        levels = [boxes]
        while len(levels[-1]) > 1:
            b, cut = levels[-1], np.arange(0, len(levels[-1]), FANOUT)
            levels.append(np.column_stack([np.minimum.reduceat(b[:, 0], cut), np.minimum.reduceat(b[:, 1], cut), np.maximum.reduceat(b[:, 2], cut), np.maximum.reduceat(b[:, 3], cut)]))
        return cls(levels)

    def leaves_meeting(self, rects: np.ndarray) -> Pairs:
        """(query, block): all queries go down the tree together."""
        return _together(self.pieces_meeting(rects))

    def pieces_meeting(self, rects: np.ndarray) -> Iterator[Pairs]:
        """The same in pieces of bounded size."""

        def down(k: int, q: np.ndarray, node: np.ndarray) -> Iterator[Pairs]:
            b, r = self.levels[k][node], rects[q]
            hit = rects_meet(r[:, 0], r[:, 1], r[:, 2], r[:, 3], b[:, 0], b[:, 1], b[:, 2], b[:, 3])
            q, node = q[hit], node[hit]
            if not k:
                yield q, node
                return
            for piece in _spread(q, node * FANOUT, np.minimum((node + 1) * FANOUT, len(self.levels[k - 1]))):
                yield from down(k - 1, *piece)

        for a in range(0, len(rects), _PIECE):
            q = np.arange(a, min(a + _PIECE, len(rects)))
            yield from down(len(self.levels) - 1, q, np.zeros(len(q), np.int64))


Probe = Callable[[np.ndarray], Iterator[Pairs]]


def _indexed(blocks: Callable) -> Callable[..., Probe]:
    """An index nested loop."""

    def over(x, y) -> Probe:
        b = blocks(x, y)
        px, py, tree = x[b.order], y[b.order], PackedTree.over(b.boxes)

        def ask(rects: np.ndarray) -> Iterator[Pairs]:
            for q, leaf in tree.pieces_meeting(rects):
                yield from _read(b, px, py, rects, q, leaf)

        return ask

    return over


def grid_probe(x, y) -> Probe:
    """Index nested loop over a uniform grid: all cells that a window covers are read, empty or not."""
    side = max(1, int(np.sqrt(len(x) / FANOUT)))
    lo, hi = (x.min(), y.min()), (x.max(), y.max())
    cell = curves.to_grid(x, lo[0], hi[0], side) * side + curves.to_grid(y, lo[1], hi[1], side)
    order = np.argsort(cell, kind="stable")
    start = np.append(0, np.cumsum(np.bincount(cell, minlength=side * side)))
    px, py = x[order], y[order]

    def ask(rects: np.ndarray) -> Iterator[Pairs]:
        cx1, cx2 = (curves.to_grid(rects[:, k], lo[0], hi[0], side) for k in (0, 2))
        cy1, cy2 = (curves.to_grid(rects[:, k], lo[1], hi[1], side) for k in (1, 3))
        for q, cx in _spread(np.arange(len(rects)), cx1, cx2 + 1):
            for some, i in _spread(q, start[cx * side + cy1[q]], start[cx * side + cy2[q] + 1]):
                yield _keep(px, py, rects, some, i, order)

    return ask


def _dual_leaves(boxes: np.ndarray, rects: np.ndarray) -> Iterator[Pairs]:
    """(query, leaf) where a window meets a leaf's box: two packed trees go down together; pairs of nodes whose boxes miss each other go."""
    cx, cy = (rects[:, 0] + rects[:, 2]) / 2, (rects[:, 1] + rects[:, 3]) / 2
    order = rtree_blocks(cx, cy).order
    cut = np.arange(0, len(rects), FANOUT)
    r = rects[order]
    qboxes = np.column_stack([np.minimum.reduceat(r[:, 0], cut), np.minimum.reduceat(r[:, 1], cut), np.maximum.reduceat(r[:, 2], cut), np.maximum.reduceat(r[:, 3], cut)])
    dt, qt = PackedTree.over(boxes), PackedTree.over(qboxes)

    def down(ql: int, dl: int, a: np.ndarray, b: np.ndarray) -> Iterator[Pairs]:
        m, n = qt.levels[ql][a], dt.levels[dl][b]
        hit = rects_meet(m[:, 0], m[:, 1], m[:, 2], m[:, 3], n[:, 0], n[:, 1], n[:, 2], n[:, 3])
        a, b = a[hit], b[hit]
        if ql == dl == 0:
            for leaf, q in _spread(b, a * FANOUT, np.minimum((a + 1) * FANOUT, len(rects))):
                q = order[q]
                n, m = boxes[leaf], rects[q]
                hit = rects_meet(m[:, 0], m[:, 1], m[:, 2], m[:, 3], n[:, 0], n[:, 1], n[:, 2], n[:, 3])
                yield q[hit], leaf[hit]
        elif ql >= dl:
            for b, a in _spread(b, a * FANOUT, np.minimum((a + 1) * FANOUT, len(qt.levels[ql - 1]))):
                yield from down(ql - 1, dl, a, b)
        else:
            for a, b in _spread(a, b * FANOUT, np.minimum((b + 1) * FANOUT, len(dt.levels[dl - 1]))):
                yield from down(ql, dl - 1, a, b)

    yield from down(len(qt.levels) - 1, len(dt.levels) - 1, np.zeros(1, np.int64), np.zeros(1, np.int64))


def dual_probe(x, y) -> Probe:
    """Two packed trees, one over the points and one over the windows of a batch."""
    d = rtree_blocks(x, y)
    px, py = x[d.order], y[d.order]

    def ask(rects: np.ndarray) -> Iterator[Pairs]:
        for q, leaf in _dual_leaves(d.boxes, rects):
            yield from _read(d, px, py, rects, q, leaf)

    return ask


def boxes_probe(boxes: np.ndarray) -> Probe:
    """(window, box) that meet: the same over boxes of shapes, whose leaves have the union of their boxes."""
    d = rtree_blocks((boxes[:, 0] + boxes[:, 2]) / 2, (boxes[:, 1] + boxes[:, 3]) / 2)
    r, cut = boxes[d.order], d.start[:-1]
    leaves = np.column_stack([np.minimum.reduceat(r[:, 0], cut), np.minimum.reduceat(r[:, 1], cut), np.maximum.reduceat(r[:, 2], cut), np.maximum.reduceat(r[:, 3], cut)])

    def ask(rects: np.ndarray) -> Iterator[Pairs]:
        for q, leaf in _dual_leaves(leaves, rects):
            for some, i in _spread(q, d.start[leaf], d.start[leaf + 1]):
                i = d.order[i]
                n, m = boxes[i], rects[some]
                hit = rects_meet(m[:, 0], m[:, 1], m[:, 2], m[:, 3], n[:, 0], n[:, 1], n[:, 2], n[:, 3])
                yield some[hit], i[hit]

    return ask


def boxes_dual_tree(boxes: np.ndarray, rects: np.ndarray) -> Pairs:
    return _together(boxes_probe(boxes)(rects)) if len(boxes) and len(rects) else _none()


def brute_probe(x, y) -> Probe:
    """Every window is held against every point's x, and those that pass against y."""

    def ask(rects: np.ndarray) -> Iterator[Pairs]:
        held, n = [], 0
        for k, (x1, y1, x2, y2) in enumerate(rects.tolist()):
            i = np.flatnonzero((x >= x1) & (x <= x2))
            i = i[(y[i] >= y1) & (y[i] <= y2)]
            held.append((np.full(len(i), k), i))
            if (n := n + len(i)) >= _PIECE:
                yield _together(held)
                held, n = [], 0
        yield _together(held)

    return ask


def sweep_probe(x, y) -> Probe:
    """No index: points in the order of x, of which a window takes its slab and tests each point's y."""
    order = np.argsort(x, kind="stable")
    px, py = x[order], y[order]

    def ask(rects: np.ndarray) -> Iterator[Pairs]:
        low, high = np.searchsorted(px, rects[:, 0]), np.searchsorted(px, rects[:, 2], "right")
        held, n = [], 0
        for k, (a, b, y1, y2) in enumerate(zip(low.tolist(), high.tolist(), rects[:, 1].tolist(), rects[:, 3].tolist())):
            if a >= b:
                continue
            i = np.flatnonzero((py[a:b] >= y1) & (py[a:b] <= y2))
            if len(i):
                held.append((np.full(len(i), k), order[a + i]))
            if (n := n + len(i)) >= _PIECE:
                yield _together(held)
                held, n = [], 0
        yield _together(held)

    return ask


PROBES: dict[str, Callable[..., Probe]] = {
    "inl_quadtree": _indexed(quadtree_blocks),
    "inl_rtree": _indexed(rtree_blocks),
    "inl_grid": grid_probe,
    "dual_tree": dual_probe,
    "brute": brute_probe,
    "sweep": sweep_probe,
}


def _whole(over: Callable[..., Probe]) -> Callable[..., Pairs]:
    return lambda x, y, rects: _together(over(x, y)(rects)) if len(x) and len(rects) else _none()


RANGE = {name: _whole(over) for name, over in PROBES.items()}
range_brute = RANGE["brute"]


# nearest neighbours -----------------------------------------------------------------------------


def _first_k(d2, pid, x, y, k: int) -> np.ndarray:
    if len(d2) > k:
        near = np.flatnonzero(d2 <= np.partition(d2, k - 1)[k - 1])
        return near[np.lexsort((y[near], x[near], pid[near], d2[near]))[:k]]
    return np.lexsort((y, x, pid, d2))[:k]


def _block_knn(blocks: Blocks, groups: list[np.ndarray], pid, x, y, qx, qy, k: int, bound: np.ndarray | None, start_bound: np.ndarray | None = None):
    """For each group of queries, reads data blocks by the distance of the boxes and stops when the next one is farther than
    every query's current k-th distance."""
    oq, oi, od = [], [], []
    limit = np.full(len(qx), np.inf) if bound is None else bound.astype(float).copy()
    if start_bound is not None:
        limit = np.minimum(limit, start_bound)
    for qs in groups:
        if len(qs) == 1:
            ids, dist = _one_knn(blocks, pid, x, y, qx[qs[0]], qy[qs[0]], k, limit[qs[0]])
            oq.append(np.full(len(ids), qs[0])), oi.append(ids), od.append(dist)
            continue
        box = np.array([[qx[qs].min(), qy[qs].min(), qx[qs].max(), qy[qs].max()]])
        far = np_box_mindist2(box, blocks.boxes)[0]
        best = [(np.zeros(0, np.int64), np.zeros(0)) for _ in qs]
        worst = limit[qs].copy()
        for b in np.argsort(far, kind="stable"):
            if far[b] > worst.max():
                break
            i = blocks.order[blocks.start[b] : blocks.start[b + 1]]
            own = np_mindist2(qx[qs], qy[qs], blocks.boxes[b : b + 1])[:, 0] <= worst
            for j in np.flatnonzero(own):
                d2 = (x[i] - qx[qs[j]]) ** 2 + (y[i] - qy[qs[j]]) ** 2
                use = d2 <= worst[j]
                ids, dist = np.append(best[j][0], i[use]), np.append(best[j][1], d2[use])
                top = _first_k(dist, pid[ids], x[ids], y[ids], k)
                best[j] = (ids[top], dist[top])
                if len(top) == k:
                    worst[j] = min(worst[j], dist[top][-1])
        for q, (ids, dist) in zip(qs, best):
            oq.append(np.full(len(ids), q)), oi.append(ids), od.append(dist)
    if not oq:
        return (*_none(), np.zeros(0))
    return np.concatenate(oq), np.concatenate(oi), np.concatenate(od)


def _one_knn(blocks: Blocks, pid, x, y, cx: float, cy: float, k: int, limit: float) -> tuple[np.ndarray, np.ndarray]:
    """One query: the nearest blocks that hold k points together give a distance, and all blocks within it are read at once."""
    far = np_mindist2(np.array([cx]), np.array([cy]), blocks.boxes)[0]
    size = np.diff(blocks.start)

    def read(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        _, i = _expand(at, blocks.start[at], blocks.start[at + 1])
        i = blocks.order[i]
        d2 = (x[i] - cx) ** 2 + (y[i] - cy) ** 2
        use = d2 <= limit
        return i[use], d2[use]

    m = min(len(far), -(-2 * k // max(1, int(size.mean()))) + 1)
    first = np.argpartition(far, m - 1)[:m] if m < len(far) else np.arange(len(far))
    ids, d2 = read(first)
    if m < len(far):
        if len(d2) >= k:
            limit = min(limit, np.partition(d2, k - 1)[k - 1])
        rest = far <= limit
        rest[first] = False
        more, d = read(np.flatnonzero(rest))
        ids, d2 = np.append(ids, more), np.append(d2, d)
    top = _first_k(d2, pid[ids], x[ids], y[ids], k)
    return ids[top], d2[top]


def _single(n: int) -> list[np.ndarray]:
    return [np.array([i]) for i in range(n)]


def _grouped(b: Blocks) -> list[np.ndarray]:
    return [b.order[s:e] for s, e in zip(b.start, b.start[1:])]


def _knn_index(blocks: Callable):
    def over(pid, x, y):
        b = blocks(x, y)
        return lambda qx, qy, k, bound=None: _block_knn(b, _single(len(qx)), pid, x, y, qx, qy, k, bound)

    return over


def _knn_blocks(data: Callable, queries: Callable):
    def over(pid, x, y):
        b = data(x, y)
        return lambda qx, qy, k, bound=None: _block_knn(b, _grouped(queries(qx, qy)), pid, x, y, qx, qy, k, bound)

    return over


def _anew(run: Callable):
    """Of a kernel that has nothing to keep from one batch of queries to the next."""
    return lambda pid, x, y: lambda qx, qy, k, bound=None: run(pid, x, y, qx, qy, k, bound)


def knn_pivot(pid, x, y, qx, qy, k, bound=None):
    """Query clusters around pivots; a pivot's own k-th distance plus a query's distance to it bounds the query's."""
    b = pivot_blocks(qx, qy, max(1, len(qx) // FANOUT))
    data, start = hilbert_blocks(x, y), np.full(len(qx), np.inf)
    if len(x) >= k:
        for qs in _grouped(b):
            px, py = qx[qs].mean(), qy[qs].mean()
            kth = np.sqrt(np.partition((x - px) ** 2 + (y - py) ** 2, k - 1)[k - 1])
            start[qs] = (kth + np.sqrt((qx[qs] - px) ** 2 + (qy[qs] - py) ** 2)) ** 2 * (1 + 1e-12) + 1e-9
    return _block_knn(data, _grouped(b), pid, x, y, qx, qy, k, bound, start)


def knn_halo(pid, x, y, qx, qy, k, bound=None):
    """Cells of queries, each joined with its own copy of the data near it: first a cell's bound is found, then the data within it."""
    groups, oq, oi, od = _grouped(grid_blocks(qx, qy, 4 * FANOUT)), [], [], []
    for qs in groups:
        cx, cy = (qx[qs].min() + qx[qs].max()) / 2, (qy[qs].min() + qy[qs].max()) / 2
        reach = np.hypot(qx[qs].max() - qx[qs].min(), qy[qs].max() - qy[qs].min()) / 2
        d = np.hypot(x - cx, y - cy)
        r = np.partition(d, k - 1)[k - 1] + 2 * reach if len(x) >= k else np.inf
        halo = np.flatnonzero(d <= r * (1 + 1e-12) + 1e-9)
        q, i, dist = knn_brute(pid[halo], x[halo], y[halo], qx[qs], qy[qs], k, None if bound is None else bound[qs])
        oq.append(qs[q]), oi.append(halo[i]), od.append(dist)
    return (np.concatenate(oq), np.concatenate(oi), np.concatenate(od)) if oq else (*_none(), np.zeros(0))


def knn_brute(pid, x, y, qx, qy, k, bound=None):
    oq, oi, od = [], [], []
    for q in range(len(qx)):
        d2 = (x - qx[q]) ** 2 + (y - qy[q]) ** 2
        i = np.arange(len(x)) if bound is None else np.flatnonzero(d2 <= bound[q])
        i = i[_first_k(d2[i], pid[i], x[i], y[i], k)]
        oq.append(np.full(len(i), q)), oi.append(i), od.append(d2[i])
    return (np.concatenate(oq), np.concatenate(oi), np.concatenate(od)) if oq else (*_none(), np.zeros(0))


def knn_sweep(pid, x, y, qx, qy, k, bound=None):
    """No index: points in the order of x. The points on both sides of a query in that order give a distance, and the slab of it is read."""
    order = np.argsort(x, kind="stable")
    px, py = x[order], y[order]
    oq, oi, od = [], [], []
    for q, (cx, cy, at) in enumerate(zip(qx.tolist(), qy.tolist(), np.searchsorted(px, qx).tolist())):
        a, b, limit = max(0, at - 32 * k), min(len(px), at + 32 * k), np.inf if bound is None else float(bound[q])
        if b - a >= k:
            limit = min(limit, np.partition((px[a:b] - cx) ** 2 + (py[a:b] - cy) ** 2, k - 1)[k - 1])
        r = np.sqrt(limit) * (1 + 1e-12)
        low, high = np.searchsorted(px, cx - r), np.searchsorted(px, cx + r, "right")
        d2 = (px[low:high] - cx) ** 2 + (py[low:high] - cy) ** 2
        near = np.flatnonzero(d2 <= limit)
        i = order[low + near]
        top = _first_k(d2[near], pid[i], x[i], y[i], k)
        oq.append(np.full(len(top), q)), oi.append(i[top]), od.append(d2[near][top])
    return (np.concatenate(oq), np.concatenate(oi), np.concatenate(od)) if oq else (*_none(), np.zeros(0))


KNN_PROBES: dict[str, Callable] = {
    "inl_quadtree": _knn_index(quadtree_blocks),
    "inl_rtree": _knn_index(rtree_blocks),
    "inl_grid": _knn_index(grid_blocks),
    "hilbert_block": _knn_blocks(hilbert_blocks, hilbert_blocks),
    "pca_block": _knn_blocks(pca_blocks, pca_blocks),
    "pivot_block": _anew(knn_pivot),
    "halo_self": _anew(knn_halo),
    "brute": _anew(knn_brute),
    "sweep": _anew(knn_sweep),
}


def _knn_whole(over: Callable) -> Callable:
    return lambda pid, x, y, qx, qy, k, bound=None: over(pid, x, y)(qx, qy, k, bound)


KNN = {name: _knn_whole(over) for name, over in KNN_PROBES.items()}


def knn_probe(algo: str, pid, x, y, k: int) -> Callable[..., Iterator[tuple[slice, np.ndarray, np.ndarray, np.ndarray]]]:
    """An index over the points, which then answers focal points in pieces of bounded size: which of them, and their (query, point,
    squared distance)."""
    ask, step = KNN_PROBES[algo](pid, x, y), max(1, _PIECE // max(1, k))

    def pieces(qx, qy, bound):
        for a in range(0, len(qx), step):
            at = slice(a, a + step)
            yield at, *ask(qx[at], qy[at], k, bound[at])

    return pieces


def knn(algo: str, pid, x, y, qx, qy, k: int, bound: np.ndarray | None = None):
    """bound: squared radii beyond which nothing is wanted."""
    if k <= 0 or not len(x) or not len(qx):
        return (*_none(), np.zeros(0))
    return KNN[algo](pid, x, y, qx, qy, k, bound)


DUAL_TREE_POINTS, R_TREE_QUERIES = 120_000, 70_000
"""Fixed values: up to so many points two R-trees beat one, and up to so many focal points an R-tree beats a space-filling curve."""


def choose(kind: str, n_data: int, n_query: int, k: int | None = None, quadtree: bool = True) -> str:
    """The local planner: quadtree nested loop for points, two trees for shapes; tiny tiles are scanned. quadtree: whether there may be
    one; without, sizes decide among the others."""
    if kind != "point":
        return "dual_tree"
    if n_data * n_query <= 4096:
        return "brute"
    if quadtree:
        return "inl_quadtree"
    if k is None:
        return "dual_tree" if n_data < DUAL_TREE_POINTS else "inl_rtree"
    return "inl_rtree" if n_query < R_TREE_QUERIES else "hilbert_block"
