"""The skew planner: which tiles to split, into how many parts, and where to cut."""

from __future__ import annotations

import heapq
import itertools
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np

from skewtile.plans.cost import CostModel, Tile

Cutter = Callable[[object, int], "list[tuple[object, Tile]]"]
"""(what identifies a tile, number of parts) -> parts, fewer if it can't be cut so far."""


@dataclass
class SplitPlan:
    """splits: for each original tile that is split (its handle, or the handle's id), its parts' handles and sizes; trails of
    cost and spare budget."""

    splits: dict[object, list[tuple[object, Tile]]] = field(default_factory=dict)
    costs: list[float] = field(default_factory=list)
    spare: list[int] = field(default_factory=list)
    n_tiles: int = 0

    @property
    def cost(self) -> float:
        return self.costs[-1]


@dataclass(order=True)
class _Entry:
    key: float
    order: int
    cost: float = field(compare=False)
    tile: Tile = field(compare=False)
    handle: object = field(compare=False)
    root: object = field(compare=False)
    carried: float = field(compare=False)
    is_split: bool = field(compare=False)


def classify(tiles: Sequence[Tile], model: CostModel, factor: float = 2.0) -> list[bool]:
    """Skewed tiles: local work above `factor` times the median."""
    work = np.array([model.local(t) for t in tiles])
    return list(work > factor * np.median(work)) if len(work) else []


def parts_wanted(model: CostModel, entry_tile: Tile, carried: float, rest_cost: float, rest_merge: float, now: float, spare: int, cut: Callable[[int], list], mode: str) -> list | None:
    """The split to try: the fewest parts that lower the plan's cost ("minimal"), two ("binary"), or the best number ("best")."""
    best = None
    for parts in range(2, spare + 1):
        made = cut(parts)
        if len(made) < 2 or len(made) < parts and best is not None:
            break
        cost = max(rest_cost, model.split(entry_tile, [t for _, t in made], carried)) + rest_merge
        if cost < now and (best is None or cost < best[0]):
            best = (cost, made)
            if mode == "minimal":
                break
        if mode == "binary" or len(made) < parts:
            break
    return best[1] if best else None


def greedy(tiles: Sequence[tuple[object, Tile]], cut: Cutter, budget: int, model: CostModel = CostModel(), mode: str = "minimal", accept_rule: str = "plan", accounting: str = "children") -> SplitPlan:
    """Splits the costliest tile while that lowers the plan's cost and parts are left.

    budget: spare parts. accounting: a split into k costs k ("children"), k - 1 ("net"), or parts may be had until there
    are `budget` tiles ("total"). accept_rule: "plan" compares whole plans, "tile" the split tile with the plan before."""
    number = itertools.count()
    name = lambda h: h if isinstance(h, (str, int)) else id(h)
    heap = [_Entry(-model.local(t), next(number), model.local(t), t, h, name(h), 0.0, False) for h, t in tiles]
    heapq.heapify(heap)
    unsplit = sum(t.n_query for _, t in tiles)
    plan = SplitPlan(n_tiles=len(heap))
    now = (-heap[0].key if heap else 0.0) + model.merge(unsplit)
    spare = budget - len(heap) if accounting == "total" else budget
    plan.costs.append(now)
    plan.spare.append(spare)
    while heap and spare >= (2 if accounting == "children" else 1):
        top = heapq.heappop(heap)
        rest_merge = model.merge(unsplit - (0 if top.is_split else top.tile.n_query))
        rest_cost = -heap[0].key if heap else 0.0
        most = spare if accounting == "children" else spare + 1
        made = parts_wanted(model, top.tile, top.carried, rest_cost, rest_merge, now, most, lambda k: cut(top.handle, k), mode)
        if made is None:
            heapq.heappush(heap, top)
            break
        parts = [t for _, t in made]
        carried = top.carried + model.reshuffle(top.tile.n_data, len(parts)) + model.merge(top.tile.n_query)
        children = [_Entry(-model.child(top.tile, t, len(parts), top.carried), next(number), 0.0, t, h, top.root, carried + model.reindex(t.n_data), True) for h, t in made]
        new = max(rest_cost, max(-c.key for c in children)) + rest_merge
        if (max(-c.key for c in children) if accept_rule == "tile" else new) >= now:
            heapq.heappush(heap, top)
            break
        for c in children:
            heapq.heappush(heap, c)
        if not top.is_split:
            unsplit -= top.tile.n_query
        plan.splits.setdefault(top.root, [])
        plan.splits[top.root] = [p for p in plan.splits[top.root] if p[0] is not top.handle] + made
        spare -= len(parts) - (accounting != "children")
        now = new
        plan.costs.append(now)
        plan.spare.append(spare)
    plan.n_tiles = len(heap)
    return plan


def brute_force(tiles: Sequence[tuple[object, Tile]], cut: Cutter, budget: int, model: CostModel = CostModel()) -> float:
    """The least plan cost over all choices of parts per tile, one split each; for small inputs only."""
    best = model.plan([t for _, t in tiles])
    for choice in itertools.product(range(1, budget + 1), repeat=len(tiles)):
        if sum(k for k in choice if k > 1) > budget:
            continue
        longest, merged = 0.0, 0.0
        for (h, t), k in zip(tiles, choice):
            made = cut(h, k) if k > 1 else []
            if len(made) > 1:
                longest = max(longest, model.split(t, [p for _, p in made]))
            else:
                longest, merged = max(longest, model.local(t)), merged + t.n_query
        best = min(best, longest + model.merge(merged))
    return best


def should_replan(before: Sequence[float], now: Sequence[float], factor: float = 2.0) -> bool:
    """Query counts per tile have drifted: the share of some tile grew by the factor, and it is above average."""
    a, b = np.asarray(before, float), np.asarray(now, float)
    if not b.sum():
        return False
    a, b = a / max(a.sum(), 1), b / b.sum()
    return bool(((b > factor * np.maximum(a, 1e-9)) & (b > 1 / len(b))).any())


@dataclass(frozen=True, eq=False)
class Histogram:
    """Data and query counts on a tile's sub-cells: (nx, ny) arrays over a box."""

    box: tuple[float, float, float, float]
    data: np.ndarray
    query: np.ndarray
    pairs: float | None = None
    """Answers expected of the whole box; parts get theirs by the product of data and queries on their sub-cells."""

    def tile(self) -> Tile:
        return Tile(float(self.data.sum()), float(self.query.sum()), self.pairs)

    def _part(self, box, where) -> Histogram:
        d, q = self.data[where], self.query[where]
        whole = float((self.data * self.query).sum())
        pairs = None if self.pairs is None else self.pairs * (float((d * q).sum()) / whole if whole else d.size / self.data.size)
        return Histogram(tuple(box), d, q, pairs)

    def _weight(self, by: str) -> np.ndarray:
        return {"data": self.data, "query": self.query, "product": self.data * self.query}[by].astype(float)

    def halves(self, by: str, share: float = 0.5) -> tuple[int, float, Histogram, Histogram] | None:
        """(axis, cut, below, above): the cell border at which the weight divides best."""
        best = None
        for a in (0, 1):
            w = self._weight(by).sum(1 - a)
            if len(w) < 2 or not w.sum():
                continue
            k = 1 + int(np.argmin(np.abs(np.cumsum(w)[:-1] - share * w.sum())))
            off = abs(w[:k].sum() - share * w.sum())
            if best is None or off < best[0]:
                best = (off, a, k)
        if best is None:
            return None
        _, a, k = best
        n = self.data.shape[a]
        c = self.box[a] + (self.box[a + 2] - self.box[a]) * k / n
        low, high = list(self.box), list(self.box)
        low[a + 2] = high[a] = c
        lower, upper = (slice(None, k), slice(None)) if a == 0 else (slice(None), slice(None, k)), (slice(k, None), slice(None)) if a == 0 else (slice(None), slice(k, None))
        return a, c, self._part(low, lower), self._part(high, upper)

    def cut(self, parts: int, by: str = "query"):
        """A nested tree of cuts, (axis, cut, below, above) or a Histogram at its leaves, with up to `parts` leaves."""
        if parts < 2 or (how := self.halves(by, (parts // 2) / parts)) is None:
            return self
        a, c, low, high = how
        return a, c, low.cut(parts // 2, by), high.cut(parts - parts // 2, by)


def leaves(tree) -> list[Histogram]:
    return [tree] if isinstance(tree, Histogram) else leaves(tree[2]) + leaves(tree[3])


def cutter(by: str = "query") -> Cutter:
    """A Cutter whose handles are nested trees; the tree of a plan's tile is got by grafting its parts (see graft)."""

    def cut(handle: Histogram, parts: int) -> list[tuple[Histogram, Tile]]:
        made = leaves(handle.cut(parts, by))
        return [(h, h.tile()) for h in made]

    return cut


def graft(handle: Histogram, kept: Sequence[Histogram]):
    """The nested tree of cuts that leaves exactly the boxes `kept` of a split tile."""
    if len(kept) == 1:
        return None
    for a in (0, 1):
        for c in sorted({h.box[a] for h in kept} - {min(h.box[a] for h in kept)}):
            low, high = [h for h in kept if h.box[a + 2] <= c], [h for h in kept if h.box[a] >= c]
            if low and high and len(low) + len(high) == len(kept):
                return a, c, graft(handle, low), graft(handle, high)
    raise ValueError("the parts of a split are no guillotine cut")
