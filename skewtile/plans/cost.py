"""The cost model: local work, routing, merging, re-shuffling and re-indexing of a tile plan."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Tile:
    """A tile's data and query counts, and the answers expected of it where they were estimated."""

    n_data: float
    n_query: float
    pairs: float | None = None


@dataclass(frozen=True)
class CostModel:
    """Weights of one unit of each kind of work. The defaults are fixed values, those of the worked example in the tests."""

    p_local: float = 0.2
    p_merge: float = 0.05
    p_shuffle: float = 0.01
    p_index: float = 0.02
    answers: float = 10.0
    p_route: float = 0.0
    local_form: Callable[[Tile], float] | None = None
    p_probe: float = 0.0
    p_pair: float = 0.0

    def local(self, t: Tile) -> float:
        """E: the local join of a tile. Where its answers were estimated from samples, probes of an index and answers are what it costs."""
        if self.local_form:
            return self.local_form(t)
        if t.pairs is not None and (self.p_probe or self.p_pair):
            return sampled_local(t.pairs, 1.0, 1.0, t.n_data, t.n_query, self.p_probe, self.p_pair)
        return t.n_data * t.n_query * self.p_local

    def route(self, n_query: float, fanout: float = 1.0) -> float:
        """epsilon: sending queries to their tiles."""
        return n_query * fanout * self.p_route

    def merge(self, n_query: float) -> float:
        """rho: merging the answers of so many routed queries."""
        return n_query * self.answers * self.p_merge

    def reshuffle(self, n_data: float, parts: int) -> float:
        """beta: dealing a tile's data to its parts."""
        return n_data * parts * self.p_shuffle

    def reindex(self, n_data: float) -> float:
        """gamma: indexing a part."""
        return n_data * self.p_index

    def plan(self, tiles: Sequence[Tile], include_route: bool = False) -> float:
        """The longest tile, then merging (and routing, on request)."""
        total = max(map(self.local, tiles), default=0.0) + self.merge(sum(t.n_query for t in tiles))
        return total + (self.route(sum(t.n_query for t in tiles)) if include_route else 0.0)

    def child(self, parent: Tile, part: Tile, parts: int, carried: float = 0.0) -> float:
        """One part's time after a split: what its parent had cost before, dealing, indexing, merging the parent's queries, joining."""
        return carried + self.reshuffle(parent.n_data, parts) + self.reindex(part.n_data) + self.merge(parent.n_query) + self.local(part)

    def split(self, parent: Tile, parts: Sequence[Tile], carried: float = 0.0) -> float:
        return max(self.child(parent, p, len(parts), carried) for p in parts)

    def plan_after(self, tiles: Sequence[Tile], at: int, parts: Sequence[Tile]) -> float:
        """The plan's cost when one tile is split."""
        rest = [t for i, t in enumerate(tiles) if i != at]
        return max(self.split(tiles[at], parts), max(map(self.local, rest), default=0.0)) + self.merge(sum(t.n_query for t in rest))


def sampled_local(pairs: float, alpha_data: float, alpha_query: float, n_data: float, n_query: float, per_probe: float = 1.0, per_pair: float = 1.0) -> float:
    """E estimated from samples: probes of an index of n_data points, and pairs found in the samples scaled up."""
    return per_probe * n_query * math.log2(n_data + 2) + per_pair * pairs / max(alpha_data * alpha_query, 1e-12)


def sample_pairs(points: np.ndarray, rects: np.ndarray) -> int:
    """How many sampled points the sampled windows hold."""
    if not len(points) or not len(rects):
        return 0
    inside = (points[:, 0][None] >= rects[:, 0][:, None]) & (points[:, 0][None] <= rects[:, 2][:, None])
    inside &= (points[:, 1][None] >= rects[:, 1][:, None]) & (points[:, 1][None] <= rects[:, 3][:, None])
    return int(inside.sum())


def calibrate(times: Sequence[tuple[Tile, float]]) -> CostModel:
    """Weights from timed local joins: seconds = p_local * |D| * |Q|, by least squares through the origin."""
    x = np.array([t.n_data * t.n_query for t, _ in times])
    y = np.array([s for _, s in times])
    return CostModel(p_local=float((x * y).sum() / max((x * x).sum(), 1e-12)))


def calibrate_sampled(times: Sequence[tuple[Tile, float]], records_per_second: float, index_seconds: float = 0.0) -> CostModel:
    """Weights in seconds from timed local joins of tiles with known answers: probes and answers by least squares, negative ones
    left out. records_per_second: how fast records are shuffled; index_seconds: what indexing a point takes."""
    x = np.array([[t.n_query * math.log2(t.n_data + 2), t.pairs] for t, _ in times], float)
    y = np.array([s for _, s in times])
    (probe, pair), *_ = np.linalg.lstsq(x, y, rcond=None)
    if probe < 0 or pair < 0:
        alone = (x * y[:, None]).sum(0) / np.maximum((x * x).sum(0), 1e-300)
        probe, pair = (alone[0], 0.0) if pair < 0 else (0.0, alone[1])
    mean = max(1e-9, x[:, 1].sum() / max(1.0, sum(t.n_query for t, _ in times)))
    per_record = 1.0 / records_per_second
    return CostModel(p_probe=float(probe), p_pair=float(pair), p_shuffle=per_record, p_merge=per_record / mean, p_index=index_seconds, answers=mean, p_local=float((x[:, 1] * y).sum() / max((x[:, 1] ** 2).sum(), 1e-300)))
