"""Convex hulls of clusters: pruning by extremes, two scans, and hulls that merge.

Hulls of partial point sets are taken batch by batch, and the hull of those hulls after a shuffle is
the hull of all points: only vertices take part in that shuffle.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..geo import kernels, polygon
from ..storage import stored

KEY = ("session_id", "seg", "cluster_id")


def prune(points: DataFrame, directions: int = 8) -> DataFrame:
    """Points that can still be hull vertices: those not strictly inside the polygon of extremes.

    ``directions`` 4 takes the least and greatest x and y; 8 also those of x + y and x - y; 0 keeps all.
    The extremes are one grouped aggregate of a fixed number of points a cluster.  ``points`` is read
    twice, so it should be a table, not a plan that clusters again.
    """
    clustered = points.where("cluster_id is not null")
    if not directions:
        return clustered
    p = F.struct(F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"))
    # in counter-clockwise order; ties take the next direction's extreme so that corners are vertices
    rank = {
        "w": F.struct(F.col("x"), -F.col("y")), "sw": F.struct(F.col("x") + F.col("y"), F.col("x")), "s": F.struct(F.col("y"), F.col("x")),
        "se": F.struct(F.col("y") - F.col("x"), F.col("y")), "e": F.struct(-F.col("x"), F.col("y")), "ne": F.struct(-F.col("x") - F.col("y"), -F.col("x")),
        "n": F.struct(-F.col("y"), -F.col("x")), "nw": F.struct(F.col("x") - F.col("y"), -F.col("y")),
    }
    names = list(rank) if directions == 8 else ["w", "s", "e", "n"]
    ext = clustered.groupBy(*KEY).agg(*(F.min_by(p, rank[d]).alias(d) for d in names)).select(*KEY, F.array(*names).alias("_ring"))
    inside = polygon.contains(F.array_distinct(F.col("_ring")), F.col("x"), F.col("y"))
    return clustered.join(ext, list(KEY)).where(~inside).select(*clustered.columns)


def _hull_rows(df: DataFrame, method: str) -> DataFrame:
    """One hull of each run of a cluster's points in a batch: few vertices go on to the last shuffle."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            frame = b.to_pandas()
            out = []
            for key, g in frame.groupby(list(KEY), sort=False):
                for x, y in _scan(list(zip(g.x.tolist(), g.y.tolist(), strict=True)), method):
                    out.append((*key, x, y))
            cols = list(zip(*out, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int64()), pa.array(cols[3], pa.float64()), pa.array(cols[4], pa.float64())], [*KEY, "x", "y"])

    return df.select("session_id", F.col("seg").cast("int"), "cluster_id", F.col("x").cast("double"), F.col("y").cast("double")).mapInArrow(rows, "session_id long, seg int, cluster_id long, x double, y double")


def _scan(points: list[tuple[float, float]], method: str) -> list[tuple[float, float]]:
    return kernels.hull_angular(points) if method == "angular" else kernels.hull_chain(points)


def convex_hull(points: DataFrame, method: str = "chain", directions: int = 8) -> DataFrame:
    """(session_id, seg, cluster_id, poly, area, n): one polygon a cluster, vertices counter-clockwise from the least.

    Clusters of one pixel, two, or pixels in a line have area 0 and are kept.
    """
    points = stored(points)
    kept = prune(points, directions)
    counts = points.where("cluster_id is not null").groupBy(*KEY).agg(F.count("*").alias("n")).withColumn("seg", F.col("seg").cast("int"))
    return with_measures(merge(_hull_rows(kept, method), method)).join(counts, list(KEY))


def merge(vertices: DataFrame, method: str = "chain") -> DataFrame:
    """(keys, poly) from rows of vertices (keys, x, y): the hull of hulls."""

    def hulls(table: pa.Table) -> pa.Table:
        """All clusters of a session in one call."""
        clusters: dict[tuple, list] = {}
        for *key, x, y in zip(*(table[c].to_pylist() for c in (*KEY, "x", "y")), strict=True):
            clusters.setdefault(tuple(key), []).append((x, y))
        polys = [[{"x": x, "y": y} for x, y in _scan(points, method)] for points in clusters.values()]
        cols = list(zip(*clusters, strict=True))
        return pa.table([*(pa.array(c, table.schema.field(n).type) for n, c in zip(KEY, cols, strict=True)), pa.array(polys, pa.list_(pa.struct([("x", pa.float64()), ("y", pa.float64())])))], [*KEY, "poly"])

    kinds = dict(vertices.dtypes)
    return vertices.groupBy("session_id").applyInArrow(hulls, ", ".join(f"{n} {kinds[n]}" for n in KEY) + f", poly {polygon.POLYGON}")


def with_measures(polys: DataFrame) -> DataFrame:
    return polys.withColumn("area", polygon.area(F.col("poly"))).withColumn("bbox", polygon.bbox(F.col("poly")))


