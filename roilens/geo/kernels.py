"""Geometry of single polygons on plain Python lists: hulls and convex clipping."""

from __future__ import annotations

import math

Point = tuple[float, float]
NEAR = 1e-9


def cross(o: Point, a: Point, b: Point) -> float:
    return (a[0] - o[0]) * (b[1] - o[1]) - (a[1] - o[1]) * (b[0] - o[0])


def hull_chain(points: list[Point], presorted: bool = False) -> list[Point]:
    """Convex hull by lower and upper chain over points in coordinate order, linear after the sort."""
    pts = points if presorted else sorted(set(points))
    if len(pts) < 3:
        return list(pts)

    def chain(seq) -> list[Point]:
        out: list[Point] = []
        for p in seq:
            while len(out) > 1 and cross(out[-2], out[-1], p) <= 0:
                out.pop()
            out.append(p)
        return out

    low, up = chain(pts), chain(reversed(pts))
    return low[:-1] + up[:-1]


def hull_angular(points: list[Point]) -> list[Point]:
    """The same hull by the textbook scan: points in order of angle about the lowest one."""
    pts = list(set(points))
    if len(pts) < 3:
        return sorted(pts)
    o = min(pts, key=lambda p: (p[1], p[0]))
    rest = sorted((p for p in pts if p != o), key=lambda p: (math.atan2(p[1] - o[1], p[0] - o[0]), (p[0] - o[0]) ** 2 + (p[1] - o[1]) ** 2))
    out = [o]
    for p in rest:
        while len(out) > 1 and cross(out[-2], out[-1], p) <= 0:
            out.pop()
        out.append(p)
    while len(out) > 2 and cross(out[-2], out[-1], o) <= 0:
        out.pop()
    first = out.index(min(out))
    return out[first:] + out[:first]


def area(poly: list[Point]) -> float:
    return abs(sum(a[0] * b[1] - b[0] * a[1] for a, b in zip(poly, poly[1:] + poly[:1], strict=True))) / 2 if len(poly) > 2 else 0.0


def clip(a: list[Point], b: list[Point]) -> list[Point]:
    """Intersection of two convex counter-clockwise polygons; empty below three vertices or 1e-9 area.

    Vertices nearer than 1e-9 to the one before are dropped, so that no edge is without length.
    """
    if len(a) < 3 or len(b) < 3:
        return []
    out = list(a)
    for p, q in zip(b, b[1:] + b[:1], strict=True):
        side = [cross(p, q, v) for v in out]
        cut: list[Point] = []
        for i, v in enumerate(out):
            j = i - 1
            if (side[i] >= 0) != (side[j] >= 0):
                t = side[j] / (side[j] - side[i])
                u = out[j]
                cut.append((u[0] + t * (v[0] - u[0]), u[1] + t * (v[1] - u[1])))
            if side[i] >= 0:
                cut.append(v)
        out = cut
        if len(out) < 3:
            return []
    slim: list[Point] = []
    for v in out:
        if not slim or math.hypot(v[0] - slim[-1][0], v[1] - slim[-1][1]) > NEAR:
            slim.append(v)
    while len(slim) > 1 and math.hypot(slim[0][0] - slim[-1][0], slim[0][1] - slim[-1][1]) <= NEAR:
        slim.pop()
    return slim if len(slim) > 2 and area(slim) > NEAR else []
