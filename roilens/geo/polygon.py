"""Convex polygons as ARRAY<STRUCT<x,y>>, counter-clockwise without repeated vertices.

Measures and predicates are Catalyst expressions; construction (hull, clip) is in ``kernels``.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

POLYGON = "array<struct<x:double,y:double>>"
ON_EDGE = 1e-7


def _next(poly: Column) -> Column:
    """The polygon turned by one vertex."""
    return F.concat(F.slice(poly, F.lit(2), F.greatest(F.size(poly) - 1, F.lit(0))), F.slice(poly, 1, 1))


def edges(poly: Column) -> Column:
    """Array of structs ax, ay, bx, by."""
    return F.zip_with(poly, _next(poly), lambda a, b: F.struct(a["x"].alias("ax"), a["y"].alias("ay"), b["x"].alias("bx"), b["y"].alias("by")))


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, v: s + v)


def _cross(e: Column) -> Column:
    return e["ax"] * e["by"] - e["bx"] * e["ay"]


def area(poly: Column) -> Column:
    return F.when(F.size(poly) < 3, 0.0).otherwise(F.abs(_sum(F.transform(edges(poly), _cross))) / 2)


def perimeter(poly: Column) -> Column:
    return _sum(F.transform(edges(poly), lambda e: F.hypot(e["bx"] - e["ax"], e["by"] - e["ay"])))


def centroid(poly: Column) -> Column:
    """Area centroid; the mean vertex of shapes without area."""
    a = area(poly)
    cx = _sum(F.transform(edges(poly), lambda e: (e["ax"] + e["bx"]) * _cross(e))) / (6 * a)
    cy = _sum(F.transform(edges(poly), lambda e: (e["ay"] + e["by"]) * _cross(e))) / (6 * a)
    mx = _sum(F.transform(poly, lambda v: v["x"])) / F.size(poly)
    my = _sum(F.transform(poly, lambda v: v["y"])) / F.size(poly)
    return F.struct(F.when(a > 0, cx).otherwise(mx).alias("x"), F.when(a > 0, cy).otherwise(my).alias("y"))


def bbox(poly: Column) -> Column:
    xs, ys = F.transform(poly, lambda v: v["x"]), F.transform(poly, lambda v: v["y"])
    return F.struct(F.array_min(xs).alias("x0"), F.array_min(ys).alias("y0"), F.array_max(xs).alias("x1"), F.array_max(ys).alias("y1"))


def contains(poly: Column, x: Column, y: Column, boundary: bool = False) -> Column:
    """Whether a point lies strictly inside (or on the boundary too); edges without length are passed over.

    Clipped vertices are rounded, so points within ``ON_EDGE`` of an edge's line count as on it.
    """

    def side(e: Column) -> Column:
        dx, dy = e["bx"] - e["ax"], e["by"] - e["ay"]
        c = dx * (y - e["ay"]) - dy * (x - e["ax"])
        near = F.lit(ON_EDGE) * F.hypot(dx, dy)
        none = (dx == 0) & (dy == 0)
        return none | ((c >= -near) if boundary else (c > near))

    return (F.size(poly) >= 3) & F.forall(edges(poly), side)


def scaled(poly: Column, ratio: Column) -> Column:
    """The polygon stretched about its centroid so that lengths grow by ``ratio``."""
    c = centroid(poly)
    return F.transform(poly, lambda v: F.struct((c["x"] + (v["x"] - c["x"]) * ratio).alias("x"), (c["y"] + (v["y"] - c["y"]) * ratio).alias("y")))


def apart(a: Column, b: Column) -> Column:
    """Whether some edge of either polygon has all of the other on its outer side: interiors are disjoint."""

    def parted(p: Column, q: Column) -> Column:
        return F.exists(
            edges(p),
            lambda e: F.forall(q, lambda v: (e["bx"] - e["ax"]) * (v["y"] - e["ay"]) - (e["by"] - e["ay"]) * (v["x"] - e["ax"]) <= 0),
        )

    return parted(a, b) | parted(b, a)


def geojson(poly: Column) -> Column:
    """GeoJSON text of a polygon, the ring closed."""
    ring = F.concat(poly, F.slice(poly, 1, 1))
    points = F.array_join(F.transform(ring, lambda v: F.concat(F.lit("["), F.round(v["x"], 6).cast("string"), F.lit(","), F.round(v["y"], 6).cast("string"), F.lit("]"))), ",")
    return F.concat(F.lit('{"type":"Polygon","coordinates":[['), points, F.lit("]]}"))
