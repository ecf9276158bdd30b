"""Cosine relevance between feedback and POIs, between POIs, and between dense vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def relevance(matched: DataFrame, facets: DataFrame, weights: DataFrame, n_attrs: int, per_roi: bool = True) -> DataFrame:
    """(session_id, roi_id, poi_id, relevance): cosine of the vector and a POI's one-hot vector.

    The sum of the vector's entries at the POI's values over norm * sqrt(number of attributes); cells
    without a row weigh w0.
    """
    keys = ["session_id", "roi_id"] if per_roi else ["session_id"]
    norm = weights.groupBy(*keys).agg(F.max("norm").alias("norm"), F.max("w0").alias("w0"))
    rows = matched.join(facets, "poi_id").join(norm, keys)
    rows = rows.join(weights.select(*keys, "attr", "val", "weight"), [*keys, "attr", "val"], "left")
    dot = F.sum(F.coalesce("weight", "w0"))
    out = rows.groupBy("session_id", "roi_id", "poi_id").agg(dot.alias("_dot"), F.max("norm").alias("_norm"))
    return out.select("session_id", "roi_id", "poi_id", F.coalesce(F.try_divide("_dot", F.col("_norm") * F.sqrt(F.lit(float(n_attrs)))), F.lit(0.0)).alias("relevance"))


def ranked(scored: DataFrame) -> DataFrame:
    """scored with ``rank`` in its region, by falling relevance; ties by poi_id."""
    w = W.partitionBy("session_id", "roi_id").orderBy(F.round("relevance", 9).desc(), "poi_id")
    return scored.withColumn("rank", F.row_number().over(w))


def poi_cosine(attrs: list[str], a: str = "a", b: str = "b") -> Column:
    """Cosine of two POIs' one-hot vectors: shared values over the number of attributes."""
    return sum((F.coalesce(F.col(f"{a}.{x}") == F.col(f"{b}.{x}"), F.lit(False)).cast("int") for x in attrs), F.lit(0)) / F.lit(float(len(attrs)))


def dense_cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays; 0 where either has no length."""

    def dot(x: Column, y: Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    return F.coalesce(F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))), F.lit(0.0))
