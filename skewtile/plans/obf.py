"""The occupancy bitmap filter: a pointer-free quadtree in two bit sequences that tells where a tile has no data.

Breadth-first, each internal node writes four bits, one per quadrant (north-west, north-east, south-east,
south-west): 1 if that child is internal too, 0 if it is a leaf. Each leaf writes one bit: 1 if data may be there. A
child's address is a rank: the k-th 1 is the (k + 1)-th internal node, the k-th 0 is the k-th leaf. Cells are
half-open towards north and east, except at the region's outer edges. A filter of I internal nodes has 7 I + 1 bits.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np

# The quadrants in the order of their bits, as (east, north).
QUADRANTS = ((0, 1), (1, 1), (1, 0), (0, 0))

Box = tuple[float, float, float, float]
GRID_DEPTH = 11
"""Filters of up to so many levels are marked on a grid of their finest cells."""


@dataclass(frozen=True)
class Filter:
    """internal: bits of internal nodes (none for a filter that is a single leaf). leaf: bits of leaves. levels: for each level
    of internal nodes, the number of its first one and the ones counted before its bits. data_version: the data that the
    emptiness was seen on."""

    box: Box
    internal: np.ndarray
    leaf: np.ndarray
    levels: tuple[tuple[int, int], ...] = ()
    version: int = 0
    data_version: int = 0

    @property
    def n_internal(self) -> int:
        return len(self.internal) // 4

    @property
    def size_bits(self) -> int:
        return len(self.internal) + len(self.leaf)

    @cached_property
    def _ones(self) -> np.ndarray:
        return np.append(0, np.cumsum(self.internal, dtype=np.int64))

    def prefix(self) -> np.ndarray:
        """Ones before each bit, and in all; counted once a filter."""
        return self._ones

    def pack(self) -> tuple[bytes, bytes]:
        return np.packbits(self.internal).tobytes(), np.packbits(self.leaf).tobytes()

    @classmethod
    def unpack(cls, box: Box, internal: bytes, leaf: bytes, n_internal: int, version: int = 0, data_version: int = 0) -> Filter:
        i = np.unpackbits(np.frombuffer(internal, np.uint8))[: 4 * n_internal].astype(bool)
        f = np.unpackbits(np.frombuffer(leaf, np.uint8))[: 3 * n_internal + 1].astype(bool)
        return cls(box, i, f, _levels(i), version, data_version)


def _levels(internal: np.ndarray) -> tuple[tuple[int, int], ...]:
    out, first, count = [], 0, 1 if len(internal) else 0
    ones = np.append(0, np.cumsum(internal, dtype=np.int64))
    while count:
        out.append((first, int(ones[4 * first])))
        nxt = int(ones[4 * (first + count)] - ones[4 * first])
        first, count = first + count, nxt
    return tuple(out)


_POP8 = np.array([bin(i).count("1") for i in range(256)], np.int64)


def rank_ones(f: Filter, at: int, mode: str = "table") -> int:
    """Ones in bits 0 to at, inclusive: by scanning, from the level's stored count, or by bytes and a table."""
    if mode == "scan":
        return int(f.internal[: at + 1].sum())
    if mode == "level":
        first, before = max((x for x in f.levels if 4 * x[0] <= at), default=(0, 0))
        return before + int(f.internal[4 * first : at + 1].sum())
    packed = np.packbits(f.internal[: at + 1])
    return int(_POP8[packed].sum())


def child(f: Filter, at: int, mode: str = "table") -> tuple[str, int]:
    """The child that bit `at` stands for: ("internal", offset of its bits) or ("leaf", its bit's place)."""
    ones = rank_ones(f, at, mode)
    return ("internal", 4 * ones) if f.internal[at] else ("leaf", at + 1 - ones - 1)


def quadrant(box: Box, q: int) -> Box:
    mx, my = (box[0] + box[2]) / 2, (box[1] + box[3]) / 2
    east, north = QUADRANTS[q]
    return (mx if east else box[0], my if north else box[1], box[2] if east else mx, box[3] if north else my)


# A tree is True or False at a leaf and a list of four trees inside.


def encode(tree, box: Box, version: int = 0, data_version: int = 0) -> Filter:
    internal: list[bool] = []
    leaf: list[bool] = []
    if isinstance(tree, bool):
        leaf.append(tree)
    level = [] if isinstance(tree, bool) else [tree]
    while level:
        nxt = []
        for node in level:
            for c in node:
                internal.append(not isinstance(c, bool))
                (leaf if isinstance(c, bool) else nxt).append(c)
        level = nxt
    bits = np.array(internal, bool)
    return Filter(box, bits, np.array(leaf, bool), _levels(bits), version, data_version)


def decode(f: Filter):
    if not f.n_internal:
        return bool(f.leaf[0])
    ones = f.prefix()

    def node(i: int):
        out = []
        for at in range(4 * i, 4 * i + 4):
            k = int(ones[at + 1])
            out.append(node(k) if f.internal[at] else bool(f.leaf[at - k]))
        return out

    return node(0)


def build(x: np.ndarray, y: np.ndarray, box: Box, max_depth: int = 7, leaf_cap: int = 1) -> Filter:
    """From a tile's points, all inside the box. A cell without points is an empty leaf; one at max_depth, or with up to
    leaf_cap points, an occupied one."""

    def cell(x: np.ndarray, y: np.ndarray, b: Box, depth: int):
        if not len(x):
            return False
        if depth == max_depth or len(x) <= leaf_cap and depth > 0:
            return True
        mx, my = (b[0] + b[2]) / 2, (b[1] + b[3]) / 2
        east, north = x >= mx, y >= my
        out = []
        for q, (e, n) in enumerate(QUADRANTS):
            use = (east == bool(e)) & (north == bool(n))
            out.append(cell(x[use], y[use], quadrant(b, q), depth + 1))
        return out

    return encode(cell(np.asarray(x, float), np.asarray(y, float), box, 0), box)


def _meets(b: Box, shape) -> bool:
    if len(shape) == 4:
        return b[0] <= shape[2] and shape[0] <= b[2] and b[1] <= shape[3] and shape[1] <= b[3]
    cx, cy, r = shape
    dx, dy = max(0.0, b[0] - cx, cx - b[2]), max(0.0, b[1] - cy, cy - b[3])
    return dx * dx + dy * dy <= r * r


def _covers(shape, b: Box) -> bool:
    if len(shape) == 4:
        return shape[0] <= b[0] and b[2] <= shape[2] and shape[1] <= b[1] and b[3] <= shape[3]
    cx, cy, r = shape
    dx, dy = max(abs(b[0] - cx), abs(b[2] - cx)), max(abs(b[1] - cy), abs(b[3] - cy))
    return dx * dx + dy * dy <= r * r


def may_contain(f: Filter, shape, ones: np.ndarray | None = None) -> bool:
    """False only if the tile has no data in the closed rectangle (x1, y1, x2, y2) or disc (x, y, r). Depth first, up to
    the first occupied leaf that the shape meets."""
    if not _meets(f.box, shape):
        return False
    if not f.n_internal:
        return bool(f.leaf[0])
    ones = f.prefix() if ones is None else ones
    stack = [(0, f.box)]
    while stack:
        i, b = stack.pop()
        for q in range(4):
            sub = quadrant(b, q)
            if not _meets(sub, shape):
                continue
            at = 4 * i + q
            k = int(ones[at + 1])
            if f.internal[at]:
                stack.append((k, sub))
            elif f.leaf[at - k]:
                return True
    return False


def may_contain_batch(f: Filter, shapes: np.ndarray) -> np.ndarray:
    """may_contain for rows of rectangles (4 columns) or discs (3 columns), as one frontier of (query, node)."""
    n = len(shapes)
    out = np.zeros(n, bool)
    if not n:
        return out
    box = np.tile(np.array(f.box, float), (n, 1))
    q = np.flatnonzero(_meets_many(box, shapes))
    if not f.n_internal:
        out[q] = bool(f.leaf[0])
        return out
    ones = f.prefix()
    node, box = np.zeros(len(q), np.int64), box[q]
    while len(q):
        nq, nn, nb = [], [], []
        mx, my = (box[:, 0] + box[:, 2]) / 2, (box[:, 1] + box[:, 3]) / 2
        for k, (east, north) in enumerate(QUADRANTS):
            sub = np.column_stack([mx if east else box[:, 0], my if north else box[:, 1], box[:, 2] if east else mx, box[:, 3] if north else my])
            at = 4 * node + k
            hit = _meets_many(sub, shapes[q])
            inner = f.internal[at]
            rank = ones[at + 1]
            leaf = hit & ~inner
            out[q[leaf][f.leaf[(at - rank)[leaf]]]] = True
            go = hit & inner
            nq.append(q[go]), nn.append(rank[go]), nb.append(sub[go])
        q, node, box = np.concatenate(nq), np.concatenate(nn), np.concatenate(nb)
        todo = ~out[q]
        q, node, box = q[todo], node[todo], box[todo]
    return out


def _meets_many(b: np.ndarray, s: np.ndarray) -> np.ndarray:
    if s.shape[1] == 4:
        return (b[:, 0] <= s[:, 2]) & (s[:, 0] <= b[:, 2]) & (b[:, 1] <= s[:, 3]) & (s[:, 1] <= b[:, 3])
    dx = np.maximum(0, np.maximum(b[:, 0] - s[:, 0], s[:, 0] - b[:, 2]))
    dy = np.maximum(0, np.maximum(b[:, 1] - s[:, 1], s[:, 1] - b[:, 3]))
    return dx * dx + dy * dy <= s[:, 2] ** 2


def _merge_equal(tree):
    """Lossless: four equal leaves become one."""
    if isinstance(tree, bool):
        return tree
    tree = [_merge_equal(c) for c in tree]
    return tree[0] if all(isinstance(c, bool) for c in tree) and len(set(tree)) == 1 else tree


def mark_empty(f: Filter, shape, border: str = "exact", max_depth: int = 9, points: tuple[np.ndarray, np.ndarray] | None = None) -> Filter:
    """Learns that the shape holds no data: cells inside it become empty, crossing ones are quartered up to max_depth.
    There they stay occupied (border "keep"), or get their true occupancy from the tile's points ("exact")."""
    if border == "exact" and points is None:
        border = "keep"

    def visit(tree, b: Box, depth: int, idx):
        if tree is False or not _meets(b, shape):
            return tree
        if _covers(shape, b):
            return False
        if isinstance(tree, bool) and depth >= max_depth:
            return True if idx is None else bool(len(idx))
        kids = [tree] * 4 if isinstance(tree, bool) else tree
        out = []
        for q, (e, n) in enumerate(QUADRANTS):
            sub = quadrant(b, q)
            part = None
            if idx is not None:
                mx, my = (b[0] + b[2]) / 2, (b[1] + b[3]) / 2
                part = idx[((points[0][idx] >= mx) == bool(e)) & ((points[1][idx] >= my) == bool(n))]
            out.append(visit(kids[q], sub, depth + 1, part))
        return out

    idx = np.arange(len(points[0])) if border == "exact" else None
    return replace(encode(_merge_equal(visit(decode(f), f.box, 0, idx)), f.box), version=f.version + 1, data_version=f.data_version)


def _edges(lo: float, hi: float, depth: int) -> np.ndarray:
    """Borders of the cells of a side after so many halvings, rounded as quadrant() rounds them."""
    e = np.array([lo, hi], float)
    for _ in range(depth):
        halved = np.empty(2 * len(e) - 1)
        halved[::2], halved[1::2] = e, (e[:-1] + e[1:]) / 2
        e = halved
    return e


def _under(side: int, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Cells of a side x side grid in any of the blocks low..high (two columns, the end left out): corners are counted and summed up."""
    use = (low < high).all(1)
    low, high = low[use], high[use]
    count = lambda i, j: np.bincount(i * (side + 1) + j, minlength=(side + 1) ** 2)
    at = count(low[:, 0], low[:, 1]) + count(high[:, 0], high[:, 1]) - count(low[:, 0], high[:, 1]) - count(high[:, 0], low[:, 1])
    return at.reshape(side + 1, side + 1).cumsum(0).cumsum(1)[:side, :side] > 0


def _to_grid(f: Filter, depth: int) -> np.ndarray:
    """What the filter says of each finest cell, by column and row; it must be no deeper than that."""
    out = np.zeros((1 << depth, 1 << depth), bool)

    def paint(tree, i: int, j: int, size: int) -> None:
        if isinstance(tree, bool):
            out[i : i + size, j : j + size] = tree
            return
        half = size // 2
        for c, (e, n) in zip(tree, QUADRANTS):
            paint(c, i + half * e, j + half * n, half)

    paint(decode(f), 0, 0, 1 << depth)
    return out


def _from_grid(grid: np.ndarray, box: Box) -> Filter:
    """The filter of the finest cells, four equal leaves being one; level by level from the root."""
    some, every = [grid], [grid]
    while len(some[0]) > 1:
        fours = lambda g: (g[::2, ::2], g[1::2, ::2], g[::2, 1::2], g[1::2, 1::2])
        some.insert(0, np.logical_or.reduce(fours(some[0])))
        every.insert(0, np.logical_and.reduce(fours(every[0])))
    if some[0][0, 0] == every[0][0, 0]:
        return encode(bool(some[0][0, 0]), box)
    i = j = np.zeros(1, np.int64)
    east, north = np.array(QUADRANTS).T
    internal, leaf = [], []
    for a, b in zip(some[1:], every[1:]):
        i, j = (2 * i[:, None] + east).ravel(), (2 * j[:, None] + north).ravel()
        a, b = a[i, j], b[i, j]
        inner = a != b
        internal.append(inner), leaf.append(b[~inner])
        i, j = i[inner], j[inner]
    bits = np.concatenate(internal)
    return Filter(box, bits, np.concatenate(leaf), _levels(bits))


def mark_all_empty(f: Filter, rects: np.ndarray, border: str = "exact", max_depth: int = 9, points: tuple[np.ndarray, np.ndarray] | None = None) -> Filter:
    """mark_empty for rows of rectangles one after another, whose order makes no difference, in one pass over the rectangles and one over the
    finest cells."""
    if len(f.levels) > max_depth or max_depth > GRID_DEPTH:
        for r in rects:
            f = mark_empty(f, tuple(r), border, max_depth, points)
        return f
    side, edges = 1 << max_depth, [_edges(f.box[k], f.box[k + 2], max_depth) for k in (0, 1)]
    first = lambda value, after: np.column_stack([np.searchsorted(e[after : after + side], value[:, k]) for k, e in enumerate(edges)])
    last = lambda value, after: np.column_stack([np.searchsorted(e[after : after + side], value[:, k], "right") for k, e in enumerate(edges)])
    low, high = rects[:, :2], rects[:, 2:]
    grid = _to_grid(f, max_depth) & ~_under(side, first(low, 0), last(high, 1))
    if border == "exact" and points is not None:
        held = np.zeros((side, side), bool)
        held[tuple(np.searchsorted(e[1:-1], p, "right") for e, p in zip(edges, points))] = True
        grid &= held | ~_under(side, first(low, 1), last(high, 0))
    return replace(_from_grid(grid, f.box), version=f.version + len(rects), data_version=f.data_version)


def visits(f: Filter, shapes) -> dict[tuple[int, ...], int]:
    """How many of the shapes visit each internal node, by its path from the root."""
    tree, seen = decode(f), {}

    def walk(t, path: tuple[int, ...], b: Box, of: list) -> None:
        of = [s for s in of if _meets(b, s)]
        if isinstance(t, bool) or not of:
            return
        seen[path] = len(of)
        for q, c in enumerate(t):
            walk(c, (*path, q), quadrant(b, q), of)

    walk(tree, (), f.box, [tuple(s) for s in shapes])
    return seen


def shrink(f: Filter, max_bits: int, policy: str = "deepest", visits: dict[tuple[int, ...], int] | None = None, prefer_lossless: bool = True) -> Filter:
    """Merges internal nodes whose children are all leaves into one leaf, occupied if any child was, until the filter fits.
    policy: "deepest" first (level order within a level), or "lru" / "mru" by a count of visits per node path."""
    tree = decode(f)
    if prefer_lossless:
        tree = _merge_equal(tree)
    nodes: list[tuple[int, ...]] = []

    def walk(t, path: tuple[int, ...]) -> None:
        if not isinstance(t, bool):
            nodes.append(path)
            for q, c in enumerate(t):
                walk(c, (*path, q))

    walk(tree, ())
    alive = set(nodes)
    seen = visits or {}
    rank = {"deepest": lambda p: (-len(p), p), "lru": lambda p: (seen.get(p, 0), -len(p), p), "mru": lambda p: (-seen.get(p, 0), -len(p), p)}[policy]

    def get(path):
        t = tree
        for q in path:
            t = t[q]
        return t

    import heapq

    ready = [(rank(p), p) for p in nodes if all(isinstance(c, bool) for c in get(p))]
    heapq.heapify(ready)
    bits = 7 * len(alive) + 1
    while bits > max_bits and ready:
        _, p = heapq.heappop(ready)
        merged = any(get(p))
        alive.discard(p)
        bits -= 7
        if not p:
            tree = merged
            break
        parent = get(p[:-1])
        parent[p[-1]] = merged
        if all(isinstance(c, bool) for c in parent):
            heapq.heappush(ready, (rank(p[:-1]), p[:-1]))
    return replace(encode(tree, f.box), version=f.version, data_version=f.data_version)


def add_points(f: Filter, x: np.ndarray, y: np.ndarray) -> Filter:
    """After an insert: the leaves of the new points become occupied, and earlier emptiness belongs to older data."""

    def visit(tree, b: Box, x, y):
        if not len(x) or tree is True:
            return tree
        if tree is False:
            return True
        mx, my = (b[0] + b[2]) / 2, (b[1] + b[3]) / 2
        return [visit(tree[q], quadrant(b, q), x[use], y[use]) for q, (e, n) in enumerate(QUADRANTS) for use in [((x >= mx) == bool(e)) & ((y >= my) == bool(n))]]

    out = encode(visit(decode(f), f.box, np.asarray(x, float), np.asarray(y, float)), f.box)
    return replace(out, version=f.version + 1, data_version=f.data_version + 1)


def merge(a: Filter, b: Filter) -> Filter:
    """What both versions agree may hold data. Only for filters of one box and one version of the data."""
    if a.box != b.box or a.data_version != b.data_version:
        raise ValueError("filters of different boxes or data can't be merged")

    def both(s, t):
        if s is False or t is False:
            return False
        if s is True or t is True:
            return t if s is True else s
        return [both(p, q) for p, q in zip(s, t)]

    out = encode(_merge_equal(both(decode(a), decode(b))), a.box)
    return replace(out, version=max(a.version, b.version) + 1, data_version=a.data_version)
