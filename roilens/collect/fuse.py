"""Fusion of several kinds of signal into one stream of weighted moves."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CORE = ("session_id", "event_id", "t_ms", "x", "y", "signal")


def fuse(signals: dict[str, tuple[DataFrame, float]]) -> DataFrame:
    """Union of signals with a weight each; event ids stay distinct by a stride per signal.

    Clustering counts a point by its weight towards ``min_pts``.
    """
    n = len(signals)
    parts = [
        df.select(*(F.col(c) if c not in ("event_id", "signal") else (F.col(c) * n + i if c == "event_id" else F.lit(kind)).alias(c) for c in CORE), F.lit(float(w)).alias("weight"))
        for i, (kind, (df, w)) in enumerate(sorted(signals.items()))
    ]
    return reduce(DataFrame.unionByName, parts)
