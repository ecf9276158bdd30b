"""Regions of interest: non-empty intersections of a session's polygons.

Pairs come from an equi-join on the session, with bounding boxes in the join and an exact separating
axis test before any clipping, so that the Arrow kernel sees pairs that do overlap.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..geo import kernels, polygon
from ..storage import stored
from .components import components


def _clipped(pairs: DataFrame) -> DataFrame:
    """pairs (session_id, src, segs, a, b) with ``poly`` = a clipped by b; empty ones dropped."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            polys, keep = [], []
            for i, (a, b) in enumerate(zip(batch.column(3).to_pylist(), batch.column(4).to_pylist(), strict=True)):
                out = kernels.clip([(v["x"], v["y"]) for v in a], [(v["x"], v["y"]) for v in b])
                if out:
                    keep.append(i)
                    polys.append([{"x": x, "y": y} for x, y in out])
            at = pa.array(keep, pa.int64())
            yield pa.RecordBatch.from_arrays([*(batch.column(c).take(at) for c in range(3)), pa.array(polys, pa.list_(pa.struct([("x", pa.float64()), ("y", pa.float64())])))], ["session_id", "src", "segs", "poly"])

    at = pairs.select("session_id", "src", F.col("segs").cast("array<int>").alias("segs"), "a", "b")
    return at.mapInArrow(rows, f"session_id long, src array<long>, segs array<int>, poly {polygon.POLYGON}")


def candidate_pairs(polys: DataFrame, pairs: str = "all") -> DataFrame:
    """Unordered pairs of a session's polygons whose interiors meet: (session_id, src, a, b)."""
    solid = polys.where("area > 1e-9").select("session_id", "seg", "cluster_id", "poly", "bbox")
    left = solid.select("session_id", F.col("seg").alias("sa"), F.col("cluster_id").alias("ca"), F.col("poly").alias("a"), F.col("bbox").alias("ba"))
    right = solid.select("session_id", F.col("seg").alias("sb"), F.col("cluster_id").alias("cb"), F.col("poly").alias("b"), F.col("bbox").alias("bb"))
    boxes = (F.col("ba.x0") < F.col("bb.x1")) & (F.col("bb.x0") < F.col("ba.x1")) & (F.col("ba.y0") < F.col("bb.y1")) & (F.col("bb.y0") < F.col("ba.y1"))
    met = left.join(right, "session_id").where((F.col("ca") < F.col("cb")) & boxes)
    if pairs == "cross_segment":
        met = met.where("sa <> sb")
    met = met.where(~polygon.apart(F.col("a"), F.col("b")))
    return met.select("session_id", F.array("ca", "cb").alias("src"), "a", "b", "sa", "sb")


def rois(polys: DataFrame, pairs: str = "all", min_support: int = 2) -> DataFrame:
    """(session_id, roi_id, poly, area, bbox, src): intersections of ``min_support`` polygons, read more than once.

    1 takes the polygons themselves; 2 is pairwise; s >= 3 extends tuples by polygons of larger id
    and other segments.  roi_id numbers a session's regions by their sources.
    """
    polys = stored(polys, "polygons")
    solid = polys.where("area > 1e-9")
    if min_support == 1:
        found = solid.select("session_id", F.array("cluster_id").alias("src"), "poly")
    else:
        met = candidate_pairs(polys, "cross_segment" if min_support > 2 else pairs)
        found = _clipped(met.withColumn("segs", F.array("sa", "sb")))
        for _ in range(min_support - 2):
            more = solid.select("session_id", F.col("cluster_id").alias("c"), F.col("seg").alias("s"), F.col("poly").alias("b"), F.col("bbox").alias("bb"))
            f = found.withColumn("fb", polygon.bbox(F.col("poly"))).withColumnRenamed("poly", "a")
            boxes = (F.col("fb.x0") < F.col("bb.x1")) & (F.col("bb.x0") < F.col("fb.x1")) & (F.col("fb.y0") < F.col("bb.y1")) & (F.col("bb.y0") < F.col("fb.y1"))
            met = f.join(more, "session_id").where((F.col("c") > F.element_at("src", -1)) & ~F.array_contains("segs", F.col("s")) & boxes & ~polygon.apart(F.col("a"), F.col("b")))
            found = _clipped(met.select("session_id", F.concat("src", F.array("c")).alias("src"), F.concat("segs", F.array("s")).alias("segs"), "a", "b"))
    out = found.withColumn("area", polygon.area(F.col("poly"))).withColumn("bbox", polygon.bbox(F.col("poly")))
    number = F.row_number().over(W.partitionBy("session_id").orderBy("src"))
    return out.withColumn("roi_id", number).select("session_id", "roi_id", "poly", "area", "bbox", "src")


def merge_rois(regions: DataFrame) -> DataFrame:
    """(session_id, roi_id, group): regions that overlap, directly or through others, share a group (its least roi_id)."""
    a = regions.select("session_id", F.col("roi_id").alias("i"), F.col("poly").alias("a"))
    b = regions.select("session_id", F.col("roi_id").alias("j"), F.col("poly").alias("b"))
    met = a.join(b, "session_id").where("i < j").where(~polygon.apart(F.col("a"), F.col("b")))
    edge = met.select(F.struct("session_id", F.col("i").alias("roi_id")).alias("a"), F.struct("session_id", F.col("j").alias("roi_id")).alias("b"))
    roots = components(edge).select(F.col("node.session_id").alias("session_id"), F.col("node.roi_id").alias("roi_id"), F.col("root.roi_id").alias("_g"))
    return regions.select("session_id", "roi_id").join(roots, ["session_id", "roi_id"], "left").select("session_id", "roi_id", F.coalesce("_g", "roi_id").alias("group"))


def discover(segmented: DataFrame, params, feedback: DataFrame | None = None) -> DataFrame:
    """Regions of segmented moves: cluster, hull, stretch by confidence, intersect."""
    from . import cluster, hull, personalize

    p = params
    polys = hull.convex_hull(cluster.dbscan(segmented, p), p.hull, p.prune_directions)
    if feedback is None:
        polys = polys.withColumn("confidence", F.lit(0.0))
    else:
        polys = polys.join(personalize.session_confidence(feedback, p.rounds_done, p.xi).select("session_id", "confidence"), "session_id", "left")
    if p.stretch_on == "polygon":
        return rois(personalize.stretch(polys, p.stretch), p.pairs, p.min_support)
    found = rois(polys, p.pairs, p.min_support).join(polys.groupBy("session_id").agg(F.max("confidence").alias("confidence")), "session_id")
    return personalize.stretch(found, p.stretch).drop("confidence", "area0")
