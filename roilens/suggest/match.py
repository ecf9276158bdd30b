"""Matching points of regions: cells first, exact containment after."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..geo import polygon, quadtree
from ..storage import stored


def match(rois: DataFrame, pois: DataFrame, leaves: DataFrame | None = None, boundary: bool = False, root: quadtree.Root = quadtree.Root()) -> DataFrame:
    """(session_id, roi_id, poi_id) of POIs inside regions.

    With ``leaves`` the regions' cells are found first and POIs come by an equi-join on cell code;
    cells wholly inside a region skip the exact test.  Without, every POI meets every region: the
    exhaustive scan the index is compared with, for small sets only.
    """
    if leaves is None:
        r = rois.select("session_id", "roi_id", "poly", polygon.bbox(F.col("poly")).alias("_b"))
        box = (F.col("mx") >= F.col("_b.x0")) & (F.col("mx") <= F.col("_b.x1")) & (F.col("my") >= F.col("_b.y0")) & (F.col("my") <= F.col("_b.y1"))
        met = pois.select("poi_id", "mx", "my").join(r, box)
        return met.where(polygon.contains(F.col("poly"), F.col("mx"), F.col("my"), boundary)).select("session_id", "roi_id", "poi_id")
    met = candidates(stored(rois, "rois"), pois, leaves, root)
    return met.where(F.col("inside") | polygon.contains(F.col("poly"), F.col("mx"), F.col("my"), boundary)).select("session_id", "roi_id", "poi_id")


def candidates(rois: DataFrame, pois: DataFrame, leaves: DataFrame, root: quadtree.Root = quadtree.Root()) -> DataFrame:
    """POIs of the leaves that a region meets, with the flag ``inside``; the polygon rides along once a cell.

    ``root`` must hold all points, as that of ``Root.around`` does.
    """
    cells = quadtree.cover(rois, leaves, root=root).join(rois.select("session_id", "roi_id", "poly"), ["session_id", "roi_id"])
    at = pois.select("poi_id", "mx", "my", "depth", "code") if "depth" in pois.columns else quadtree.member(pois.select("poi_id", "mx", "my"), leaves, root)
    return at.join(cells, ["depth", "code"]).select("session_id", "roi_id", "poi_id", "mx", "my", "poly", "inside")


def out_of_sight(matched: DataFrame, pois: DataFrame, moves: DataFrame, radius: int) -> DataFrame:
    """Matches whose POI lies farther than ``radius`` from every move of the session, by a join on grid cells."""
    m = matched.join(pois.select("poi_id", "mx", "my"), "poi_id")
    near = m.withColumn("_i", F.explode(F.array(*map(F.lit, (-1, 0, 1))))).withColumn("_j", F.explode(F.array(*map(F.lit, (-1, 0, 1)))))
    near = near.withColumn("gx", F.floor(F.col("mx") / radius) + F.col("_i")).withColumn("gy", F.floor(F.col("my") / radius) + F.col("_j"))
    seen = moves.select("session_id", "x", "y", F.floor(F.col("x") / radius).alias("gx"), F.floor(F.col("y") / radius).alias("gy")).distinct()
    hit = near.join(seen, ["session_id", "gx", "gy"]).where((F.col("mx") - F.col("x")) ** 2 + (F.col("my") - F.col("y")) ** 2 <= radius * radius)
    return matched.join(hit.select("session_id", "poi_id").distinct(), ["session_id", "poi_id"], "left_anti").select("session_id", "roi_id", "poi_id")
