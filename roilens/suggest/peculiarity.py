"""Peculiarity of regions, and how many highlights it grants."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def score(vectors: DataFrame, weights: DataFrame, per_roi: bool = True) -> DataFrame:
    """(session_id, roi_id, printed, intent): cosine of the feedback and a region's binary vector, and 1 less it."""
    keys = ["session_id", "roi_id"] if per_roi else ["session_id"]
    norm = weights.groupBy(*keys).agg(F.max("norm").alias("norm"), F.max("w0").alias("w0"))
    rows = vectors.join(norm, keys).join(weights.select(*keys, "attr", "val", "weight"), [*keys, "attr", "val"], "left")
    out = rows.groupBy("session_id", "roi_id").agg(F.sum(F.coalesce("weight", "w0")).alias("_dot"), F.max("norm").alias("_norm"), F.count("*").alias("_n"))
    cos = F.coalesce(F.try_divide("_dot", F.col("_norm") * F.sqrt(F.col("_n").cast("double"))), F.lit(0.0))
    return out.select("session_id", "roi_id", cos.alias("printed")).withColumn("intent", 1 - F.col("printed"))


def k_prime(peculiarity: Column, k: int, mode: str = "printed") -> Column:
    """floor(k * peculiarity), values within 1e-9 of a whole number taken for it; 'plain' is k itself."""
    return F.lit(k) if mode == "plain" else F.floor(F.lit(k) * peculiarity + F.lit(1e-9)).cast("int")
