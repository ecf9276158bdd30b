"""Density clustering of each segment's points, with a distance threshold and a core count.

Small segments are clustered by a vectorised kernel, one call a session; segments over a cap go to a
distributed grid method that gives the same clusters.  Points of one pixel are folded into a weight
first (a count, not a repeat).  Labels do not depend on input order: a cluster is named by the least
event_id among its core points, a border point joins the cluster of its nearest core point, ties by
the smaller name; noise has no cluster.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..params import Params
from ..storage import stored, written
from .components import components

BLOCK = 1024


def dbscan_arrays(
    x: np.ndarray, y: np.ndarray, event_id: np.ndarray, radius: float, min_pts: int, strict: bool = True, count_self: bool = True,
    t: np.ndarray | None = None, eps_t: float | None = None, weight: np.ndarray | None = None, delta_mean: float | None = None,
) -> tuple[np.ndarray, np.ndarray]:
    """(cluster names, -1 for noise; roles 2 core, 1 border, 0 noise) of one segment's points.

    Neighbours are looked up block by block, so memory is n * BLOCK at most.  ``eps_t`` also bounds
    the time between neighbours; ``delta_mean`` keeps a core point from linking cores farther than
    that from its neighbourhood's mean.
    """
    n = len(x)
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.int8)
    w = np.ones(n) if weight is None else weight
    xy = np.column_stack([x, y]).astype(float)

    def near(rows: np.ndarray) -> np.ndarray:
        d = (xy[rows, None, 0] - xy[None, :, 0]) ** 2 + (xy[rows, None, 1] - xy[None, :, 1]) ** 2
        ok = d < radius * radius if strict else d <= radius * radius
        if eps_t is not None and t is not None:
            ok &= np.abs(t[rows, None] - t[None, :]) <= eps_t
        return ok

    blocks = [np.arange(i, min(i + BLOCK, n)) for i in range(0, n, BLOCK)]
    count = np.concatenate([near(b) @ w for b in blocks]) - (0 if count_self else 1)
    core = count >= min_pts
    name = np.where(core, event_id, np.iinfo(np.int64).max)
    cores = np.flatnonzero(core)
    while len(cores):  # least name among linked cores, until nothing changes
        new = name.copy()
        for i in range(0, len(cores), BLOCK):
            rows = cores[i : i + BLOCK]
            link = near(rows)[:, cores]
            if delta_mean is not None:
                mean = np.array([xy[cores[r]].mean(0) for r in link])
                far = np.hypot(xy[cores][None, :, 0] - mean[:, None, 0], xy[cores][None, :, 1] - mean[:, None, 1])
                link &= (far <= delta_mean) | (rows[:, None] == cores[None, :])
            new[rows] = np.minimum(new[rows], np.where(link, name[cores][None, :], np.iinfo(np.int64).max).min(1))
            if delta_mean is not None:
                for r, row in enumerate(rows):
                    np.minimum.at(new, cores[link[r]], new[row])
        if (new == name).all():
            break
        name = new
    cluster = np.where(core, name, -1)
    role = np.where(core, 2, 0).astype(np.int8)
    others = np.flatnonzero(~core)
    for i in range(0, len(others), BLOCK):
        rows = others[i : i + BLOCK]
        if not len(cores):
            break
        d = (xy[rows, None, 0] - xy[None, cores, 0]) ** 2 + (xy[rows, None, 1] - xy[None, cores, 1]) ** 2
        d = np.where(near(rows)[:, cores], d, np.inf)
        least = d.min(1)
        best = np.where(d == least[:, None], name[cores][None, :], np.iinfo(np.int64).max).min(1)
        hit = np.isfinite(least)
        cluster[rows[hit]] = best[hit]
        role[rows[hit]] = 1
    return cluster, role


ROLES = np.array(["noise", "border", "core"])


def _local(points: DataFrame, p: Params) -> DataFrame:
    schema = T.StructType([*points.schema, T.StructField("cluster_id", T.LongType()), T.StructField("role", T.StringType())])

    def kernel(table: pa.Table) -> pa.Table:
        seg = table["seg"].to_numpy()
        cluster, role = np.full(len(seg), -1, np.int64), np.zeros(len(seg), np.int8)
        x, y, e, t = (table[c].to_numpy() for c in ("x", "y", "event_id", "t_ms"))
        mass = table["weight"].to_numpy() if "weight" in table.column_names else np.ones(len(seg))
        for s in np.unique(seg):
            at = np.flatnonzero(seg == s)
            # pixels once, with weights, unless time separates equal pixels
            if p.eps_t is None and p.count_self and p.delta_mean is None:
                pixel, first, back = np.unique(np.column_stack([x[at], y[at]]), axis=0, return_index=True, return_inverse=True)
                least = np.full(len(pixel), np.iinfo(np.int64).max)
                np.minimum.at(least, back.ravel(), e[at])
                c, r = dbscan_arrays(pixel[:, 0], pixel[:, 1], least, p.radius, p.min_pts, p.strict, True, weight=np.bincount(back.ravel(), mass[at]))
                cluster[at], role[at] = c[back.ravel()], r[back.ravel()]
            else:
                cluster[at], role[at] = dbscan_arrays(x[at], y[at], e[at], p.radius, p.min_pts, p.strict, p.count_self, t[at], p.eps_t, mass[at], p.delta_mean)
        out = table.append_column("cluster_id", pa.array(cluster, pa.int64(), mask=cluster < 0))
        return out.append_column("role", pa.array(ROLES[role]))

    return points.groupBy("session_id").applyInArrow(kernel, schema)


def _cells(points: DataFrame, side: float) -> DataFrame:
    return points.withColumn("cx", F.floor(F.col("x") / F.lit(side))).withColumn("cy", F.floor(F.col("y") / F.lit(side)))


def distributed(points: DataFrame, p: Params) -> DataFrame:
    """The same clusters by equi-joins on a grid of side radius / sqrt(2).

    Points of one cell are neighbours of each other, so clusters are components of cells; only the 21
    cells around one can hold neighbours.  Pixels are folded into weights before any join.  Joins are
    hinted: Spark takes sizes from files and does not count what explode adds, and would send large
    tables through the driver.
    """
    key = ["session_id", "seg"]
    mass = F.sum("weight") if "weight" in points.columns else F.count("*")
    side = p.radius / math.sqrt(2) * (1 - 1e-9)
    pixels = written(_cells(points.groupBy(*key, "x", "y").agg(mass.alias("w"), F.min("event_id").alias("e")), side), "pixels")
    around = [(i, j) for i in range(-2, 3) for j in range(-2, 3) if abs(i) + abs(j) < 4]
    offsets = F.array(*(F.struct(F.lit(i).cast("long").alias("i"), F.lit(j).cast("long").alias("j")) for i, j in around))

    def joined(left: DataFrame, right: DataFrame) -> DataFrame:
        spread = left.withColumn("_o", F.explode(offsets)).withColumn("_cx", F.col("cx") + F.col("_o.i")).withColumn("_cy", F.col("cy") + F.col("_o.j")).drop("_o")
        r = right.select(*(F.col(c).alias(f"r_{c}") for c in right.columns))
        pair = spread.join(r.hint("merge"), (F.col("session_id") == F.col("r_session_id")) & (F.col("seg") == F.col("r_seg")) & (F.col("_cx") == F.col("r_cx")) & (F.col("_cy") == F.col("r_cy")))
        d2 = (F.col("x") - F.col("r_x")) ** 2 + (F.col("y") - F.col("r_y")) ** 2
        return pair.withColumn("d2", d2).where((F.col("d2") < p.radius**2) if p.strict else (F.col("d2") <= p.radius**2))

    counts = joined(pixels, pixels).groupBy(*key, "x", "y").agg(F.sum("r_w").alias("near"))
    core = counts.where(F.col("near") - (0 if p.count_self else 1) >= p.min_pts).drop("near")
    cores = written(pixels.join(core.hint("merge"), [*key, "x", "y"]), "cores")
    cell_id = F.struct("session_id", "seg", "cx", "cy")
    named = written(cores.groupBy(*key, "cx", "cy").agg(F.min("e").alias("cell_e")), "cells")
    far = F.struct(F.col("r_session_id").alias("session_id"), F.col("r_seg").alias("seg"), F.col("r_cx").alias("cx"), F.col("r_cy").alias("cy"))
    edges = joined(cores, cores).select(cell_id.alias("a"), far.alias("b")).where("a < b").distinct()
    roots = components(edges)
    own = named.withColumn("_cell", cell_id).join(roots.hint("merge"), F.col("_cell") == F.col("node"), "left").withColumn("_root", F.coalesce("root", "_cell"))
    least = own.groupBy("_root").agg(F.min("cell_e").alias("cluster_id")).withColumnRenamed("_root", "_r")
    labelled = written(cores.join(own.join(least.hint("merge"), F.col("_root") == F.col("_r")).select(*key, "cx", "cy", "cluster_id").hint("merge"), [*key, "cx", "cy"]), "core-labels")
    rest = pixels.join(core.hint("merge"), [*key, "x", "y"], "left_anti")
    near = joined(rest, labelled).groupBy(*key, "x", "y").agg(F.min(F.struct("d2", "r_cluster_id")).alias("m")).select(*key, "x", "y", F.col("m.r_cluster_id").alias("cluster_id"), F.lit("border").alias("role"))
    marks = labelled.select(*key, "x", "y", "cluster_id", F.lit("core").alias("role")).unionByName(near)
    return points.join(marks.hint("merge"), [*key, "x", "y"], "left").withColumn("role", F.coalesce("role", F.lit("noise"))).select(*points.columns, "cluster_id", "role")


def dbscan(points: DataFrame, params: Params = Params()) -> DataFrame:
    """points (session_id, seg, event_id, t_ms, x, y, ...) with ``cluster_id`` and ``role``.

    Where there is a column ``weight`` (fused signals), a point counts by it towards ``min_pts``.

    The router counts each session's distinct pixels; sessions over ``local_cap`` take the distributed
    way.  Temporal options are local only, as they need single points.
    """
    p = params
    if p.eps_t is not None or p.delta_mean is not None:
        return _local(points, p)
    sizes = points.groupBy("session_id").agg(F.count("*").alias("n")).where(F.col("n") > p.local_cap).select("session_id")
    if not sizes.take(1):
        return _local(points, p)
    sizes = written(sizes, "large")
    return _local(points.join(sizes, "session_id", "left_anti"), p).unionByName(distributed(points.join(sizes, "session_id", "left_semi"), p))


def roles(clustered: DataFrame) -> DataFrame:
    """(session_id, seg, cores, borders, noise, clusters)."""
    return clustered.groupBy("session_id", "seg").agg(
        F.count_if(F.col("role") == "core").alias("cores"), F.count_if(F.col("role") == "border").alias("borders"),
        F.count_if(F.col("role") == "noise").alias("noise"), F.count_distinct("cluster_id").alias("clusters"),
    )


def reachable(points: DataFrame, params: Params = Params()) -> DataFrame:
    """(session_id, seg, a, b): pairs of points directly reachable from each other, a < b.

    A range join through grid cells of side radius, so that a point meets its own and eight other cells only.
    """
    p = params
    g = points.withColumn("cx", F.floor(F.col("x") / p.radius)).withColumn("cy", F.floor(F.col("y") / p.radius))
    spread = g.withColumn("_i", F.explode(F.array(*map(F.lit, (-1, 0, 1))))).withColumn("_j", F.explode(F.array(*map(F.lit, (-1, 0, 1)))))
    left = spread.select("session_id", "seg", F.col("event_id").alias("a"), "x", "y", (F.col("cx") + F.col("_i")).alias("cx"), (F.col("cy") + F.col("_j")).alias("cy"))
    right = g.select("session_id", "seg", F.col("event_id").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"), "cx", "cy")
    d2 = (F.col("x") - F.col("bx")) ** 2 + (F.col("y") - F.col("by")) ** 2
    ok = (d2 < p.radius**2) if p.strict else (d2 <= p.radius**2)
    return left.join(right, ["session_id", "seg", "cx", "cy"]).where((F.col("a") < F.col("b")) & ok).select("session_id", "seg", "a", "b")


def linked(points: DataFrame, params: Params = Params()) -> DataFrame:
    """(event_id, root): core points and the least core point that a chain of core points leads to."""
    p = params
    pairs = stored(reachable(points, p), "reachable")
    ends = pairs.select(F.col("a").alias("event_id")).unionAll(pairs.select(F.col("b").alias("event_id"))).groupBy("event_id").agg(F.count("*").alias("near"))
    core = points.select("event_id").join(ends, "event_id", "left").where(F.coalesce("near", F.lit(0)) + int(p.count_self) >= p.min_pts).select("event_id")
    core = stored(core, "cores")
    edges = pairs.select("a", "b").join(core.select(F.col("event_id").alias("a")), "a").join(core.select(F.col("event_id").alias("b")), "b").select("a", "b")
    roots = components(edges).select(F.col("node").alias("event_id"), "root")
    return core.join(roots, "event_id", "left").select("event_id", F.coalesce("root", "event_id").alias("root"))


def density_surface(moves: DataFrame, side: int = 50) -> DataFrame:
    """(session_id, gx, gy, n): moves per square of the screen, interest as density."""
    return moves.groupBy("session_id", F.floor(F.col("x") / side).alias("gx"), F.floor(F.col("y") / side).alias("gy")).agg(F.count("*").alias("n"))
