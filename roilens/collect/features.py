"""Speed and dwell of a signal: what tells a look from a passing move."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def kinematics(moves: DataFrame) -> DataFrame:
    """moves with dt_ms and dist since the move before, speed (px per s) and dwell_ms until the next."""
    w = W.partitionBy("session_id").orderBy("t_ms", "event_id")
    dx, dy = F.col("x") - F.lag("x").over(w), F.col("y") - F.lag("y").over(w)
    out = moves.withColumn("dt_ms", F.col("t_ms") - F.lag("t_ms").over(w)).withColumn("dist", F.sqrt((dx * dx + dy * dy).cast("double")))
    return out.withColumn("speed", F.try_divide(F.col("dist") * 1000.0, F.col("dt_ms"))).withColumn("dwell_ms", F.lead("t_ms").over(w) - F.col("t_ms"))


def dwell_by(moves: DataFrame, *keys: str) -> DataFrame:
    """Total dwell by item features (any columns): time spent, number of looks."""
    return kinematics(moves).groupBy(*keys).agg(F.sum("dwell_ms").alias("dwell_ms"), F.count("*").alias("looks"))
