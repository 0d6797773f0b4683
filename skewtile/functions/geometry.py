"""Predicates and distances, as Columns and as numpy. Ranges are closed; distances are squared where they can be."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_M = 6_371_000.0


def in_rect(x: Column, y: Column, x1, y1, x2, y2) -> Column:
    return x.between(x1, x2) & y.between(y1, y2)


def dist2(x: Column, y: Column, cx, cy) -> Column:
    dx, dy = x - cx, y - cy
    return dx * dx + dy * dy


def in_circle(x: Column, y: Column, cx, cy, r) -> Column:
    """The square window comes first: it is what scans push down."""
    r = F.lit(r) if not isinstance(r, Column) else r
    return x.between(cx - r, cx + r) & y.between(cy - r, cy + r) & (dist2(x, y, cx, cy) <= r * r)


def rects_meet(ax1, ay1, ax2, ay2, bx1, by1, bx2, by2):
    """Works on Columns and on arrays."""
    return (ax1 <= bx2) & (bx1 <= ax2) & (ay1 <= by2) & (by1 <= ay2)


def mindist2(px: Column, py: Column, x1, y1, x2, y2) -> Column:
    """From a point to the nearest point of a rectangle."""
    dx = F.greatest(F.lit(0.0), x1 - px, px - x2)
    dy = F.greatest(F.lit(0.0), y1 - py, py - y2)
    return dx * dx + dy * dy


def maxdist2(px: Column, py: Column, x1, y1, x2, y2) -> Column:
    """From a point to the farthest point of a rectangle."""
    dx, dy = F.greatest(F.abs(px - x1), F.abs(px - x2)), F.greatest(F.abs(py - y1), F.abs(py - y2))
    return dx * dx + dy * dy


def rect_mindist2(ax1: Column, ay1: Column, ax2: Column, ay2: Column, bx1, by1, bx2, by2) -> Column:
    dx = F.greatest(F.lit(0.0), bx1 - ax2, ax1 - bx2)
    dy = F.greatest(F.lit(0.0), by1 - ay2, ay1 - by2)
    return dx * dx + dy * dy


def haversine_m(lon1: Column, lat1: Column, lon2: Column, lat2: Column) -> Column:
    """Great-circle distance in metres between points in degrees."""
    a = F.pow(F.sin((F.radians(lat2) - F.radians(lat1)) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin((F.radians(lon2) - F.radians(lon1)) / 2), 2)
    return 2 * EARTH_M * F.asin(F.least(F.lit(1.0), F.sqrt(a)))


def np_mindist2(px, py, box: np.ndarray) -> np.ndarray:
    """Points (m) against boxes (n, 4): m x n."""
    dx = np.maximum(0, np.maximum(box[:, 0] - px[:, None], px[:, None] - box[:, 2]))
    dy = np.maximum(0, np.maximum(box[:, 1] - py[:, None], py[:, None] - box[:, 3]))
    return dx * dx + dy * dy


def np_maxdist2(px, py, box: np.ndarray) -> np.ndarray:
    dx = np.maximum(abs(px[:, None] - box[:, 0]), abs(px[:, None] - box[:, 2]))
    dy = np.maximum(abs(py[:, None] - box[:, 1]), abs(py[:, None] - box[:, 3]))
    return dx * dx + dy * dy


def np_box_mindist2(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Boxes (m, 4) against boxes (n, 4): m x n."""
    dx = np.maximum(0, np.maximum(b[:, 0] - a[:, None, 2], a[:, None, 0] - b[:, 2]))
    dy = np.maximum(0, np.maximum(b[:, 1] - a[:, None, 3], a[:, None, 1] - b[:, 3]))
    return dx * dx + dy * dy


def _turn(o, a, b) -> float:
    return (a[0] - o[0]) * (b[1] - o[1]) - (a[1] - o[1]) * (b[0] - o[0])


def _on(a, b, p) -> bool:
    return _turn(a, b, p) == 0 and min(a[0], b[0]) <= p[0] <= max(a[0], b[0]) and min(a[1], b[1]) <= p[1] <= max(a[1], b[1])


def segments_meet(a, b, c, d) -> bool:
    """Closed segments a-b and c-d share a point."""
    t1, t2, t3, t4 = _turn(a, b, c), _turn(a, b, d), _turn(c, d, a), _turn(c, d, b)
    if ((t1 > 0) != (t2 > 0)) and ((t3 > 0) != (t4 > 0)) and 0 not in (t1, t2, t3, t4):
        return True
    return _on(a, b, c) or _on(a, b, d) or _on(c, d, a) or _on(c, d, b)


def point_in_polygon(p, ring) -> bool:
    """Inside or on the border of a simple polygon."""
    inside = False
    for a, b in zip(ring, [*ring[1:], ring[0]]):
        if _on(a, b, p):
            return True
        if (a[1] > p[1]) != (b[1] > p[1]) and p[0] < (b[0] - a[0]) * (p[1] - a[1]) / (b[1] - a[1]) + a[0]:
            inside = not inside
    return inside


def _edges(kind: str, pts) -> list:
    if len(pts) == 1:
        return [(pts[0], pts[0])]
    return list(zip(pts, pts[1:])) + ([(pts[-1], pts[0])] if kind in ("polygon", "rect") and len(pts) > 2 else [])


def shapes_intersect(kind_a: str, a, kind_b: str, b) -> bool:
    """Exact test of two shapes: point, segment, polyline, rect or polygon, as lists of vertices."""
    if any(segments_meet(*s, *t) for s in _edges(kind_a, a) for t in _edges(kind_b, b)):
        return True
    area = ("polygon", "rect")
    return kind_a in area and point_in_polygon(b[0], a) or kind_b in area and point_in_polygon(a[0], b)


def shape_contains(kind_a: str, a, kind_b: str, b) -> bool:
    """a is an area, b lies in it, border included."""
    if kind_a not in ("polygon", "rect") or not all(point_in_polygon(p, a) for p in b):
        return False
    proper = lambda s, t: _turn(*s, t[0]) * _turn(*s, t[1]) < 0 and _turn(*t, s[0]) * _turn(*t, s[1]) < 0
    return not any(proper(s, t) for s in _edges(kind_a, a) for t in _edges(kind_b, b))


def segment_distance2(p, a, b) -> float:
    dx, dy = b[0] - a[0], b[1] - a[1]
    t = 0.0 if dx == dy == 0 else min(1.0, max(0.0, ((p[0] - a[0]) * dx + (p[1] - a[1]) * dy) / (dx * dx + dy * dy)))
    return (p[0] - a[0] - t * dx) ** 2 + (p[1] - a[1] - t * dy) ** 2


def shapes_within(kind_a: str, a, kind_b: str, b, r: float) -> bool:
    """The shapes come within distance r of each other."""
    if shapes_intersect(kind_a, a, kind_b, b):
        return True
    ea, eb = _edges(kind_a, a), _edges(kind_b, b)
    return min(min(segment_distance2(p, *e) for p in a for e in eb), min(segment_distance2(p, *e) for p in b for e in ea)) <= r * r
