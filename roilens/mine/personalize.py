"""User confidence and the stretching of areas by it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..geo import polygon


def confidence(nnz: Column, rounds: Column | int, xi: float = 7.0) -> Column:
    """min(1, touched facets / (signals an interaction * interactions)); 0 of nothing, 1 where no interaction is counted."""
    seen = F.lit(xi) * (F.lit(rounds) if isinstance(rounds, int) else rounds)
    return F.when(nnz == 0, 0.0).when(seen == 0, 1.0).otherwise(F.least(F.lit(1.0), nnz / seen))


def session_confidence(feedback: DataFrame, rounds: int, xi: float = 7.0) -> DataFrame:
    """(session_id, nnz, confidence) from raw feedback rows."""
    return feedback.groupBy("session_id").agg(F.count_if(F.col("raw") > 0).alias("nnz")).withColumn("confidence", confidence(F.col("nnz"), rounds, xi))


def factor(conf: Column, mode: str) -> Column:
    """Ratio of new to old area: 1 + c as printed, 2 - c as the prose intends, 1 for none."""
    return {"printed": 1 + conf, "intent": 2 - conf, "none": F.lit(1.0)}[mode]


def stretch(polys: DataFrame, mode: str = "printed", conf: str = "confidence") -> DataFrame:
    """polys with ``poly`` scaled about its centroid to the new ``area``; ``area0`` keeps the old one."""
    c = F.coalesce(F.col(conf), F.lit(0.0))
    out = polys.withColumn("area0", F.col("area"))
    if mode != "none":
        out = out.withColumn("poly", F.when(F.col("area") > 0, polygon.scaled(F.col("poly"), F.sqrt(factor(c, mode)))).otherwise(F.col("poly")))
        out = out.withColumn("area", F.col("area0") * factor(c, mode))
    return out.withColumn("bbox", polygon.bbox(F.col("poly")))
