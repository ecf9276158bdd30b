"""Equirectangular projection between screen pixels and map degrees, as column arithmetic."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

# The carriers' viewport.
GAMMA, THETA, PX_PER_DEG = 48.86, 2.30, 10000.0


def _cos(gamma: Column | float) -> Column:
    if isinstance(gamma, (int, float)):
        if abs(gamma) >= 90:
            raise ValueError("the centre's latitude must lie strictly between -90 and 90 degrees")
        return F.lit(math.cos(math.radians(gamma)))
    bad = F.raise_error(F.lit("the centre's latitude must lie strictly between -90 and 90 degrees"))
    return F.when(F.abs(gamma) < 90, F.cos(F.radians(gamma))).otherwise(bad.cast("double"))


def to_map(x: Column, y: Column, gamma: Column | float = GAMMA, theta: Column | float = THETA, ppd: Column | float = PX_PER_DEG) -> tuple[Column, Column]:
    """(lat, lon) of a pixel; ``ppd`` pixels stand for a degree (1 takes pixels for degrees)."""
    g, t, s = (F.lit(v) if isinstance(v, (int, float)) else v for v in (gamma, theta, ppd))
    return (y / s + g).alias("lat"), (x / s / _cos(gamma) + t).alias("lon")


def to_screen(lat: Column, lon: Column, gamma: Column | float = GAMMA, theta: Column | float = THETA, ppd: Column | float = PX_PER_DEG) -> tuple[Column, Column]:
    """(x, y) of a place: the inverse of ``to_map``."""
    g, t, s = (F.lit(v) if isinstance(v, (int, float)) else v for v in (gamma, theta, ppd))
    return ((lon - t) * _cos(gamma) * s).alias("x"), ((lat - g) * s).alias("y")


def with_viewport(moves: DataFrame, viewports: DataFrame) -> DataFrame:
    """moves with lat, lon by the viewport (session_id, t_ms, gamma, theta, ppd) in force at their time.

    An as-of join without a join: viewport changes are rows of the same stream, and the last one seen
    is carried forward.  Moves before the first change have no place.
    """
    v = viewports.select("session_id", "t_ms", F.struct("gamma", "theta", "ppd").alias("_v"))
    both = moves.unionByName(v, allowMissingColumns=True).withColumn("_kind", F.col("_v").isNull().cast("int"))
    w = W.partitionBy("session_id").orderBy("t_ms", "_kind").rowsBetween(W.unboundedPreceding, W.currentRow)
    seen = both.withColumn("_at", F.last("_v", ignorenulls=True).over(w)).where("_kind = 1")
    lat, lon = to_map(F.col("x"), F.col("y"), F.col("_at.gamma"), F.col("_at.theta"), F.col("_at.ppd"))
    return seen.withColumn("lat", F.when(F.col("_at").isNotNull(), lat)).withColumn("lon", F.when(F.col("_at").isNotNull(), lon)).select(*moves.columns, "lat", "lon")
