"""Greedy highlights: the most relevant points of each region, swapped for diversity while similar enough."""

from __future__ import annotations

import time
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..params import Params

SCHEMA = "session_id long, roi_id int, rank int, poi_id long, relevance double, k_prime int, scanned int, stop_reason string"


def similarity(a: tuple, b: tuple) -> float:
    return sum(x is not None and x == y for x, y in zip(a, b, strict=True)) / len(a)


def set_diversity(items: list[tuple], how: str = "mean") -> float:
    """Diversity of a set: mean, sum or least cosine distance over its pairs; 0 below two."""
    d = [1 - similarity(a, b) for i, a in enumerate(items) for b in items[i + 1 :]]
    if not d:
        return 0.0
    return {"mean": sum(d) / len(d), "sum": sum(d), "min": min(d)}[how]


def swap_scan(
    items: list[tuple], k: int, threshold: float = 0.3, guard: str = "intent", swap: str = "first", diversity: str = "mean",
    max_scan: int | None = None, time_limit_ms: int | None = None, clock: Callable[[], float] = time.monotonic,
) -> tuple[list[int], int, str]:
    """(chosen indices, points scanned, why it stopped) over points' attribute tuples in order of relevance.

    For mean and sum a swap changes only the pairs of the point that leaves, so a test costs O(k).
    """
    chosen = list(range(min(k, len(items))))
    if not chosen:
        return [], 0, "empty"
    until = None if time_limit_ms is None else clock() + time_limit_ms / 1000
    best = items[0]
    scanned, at = 0, len(chosen)
    while True:
        if at >= len(items):
            return chosen, scanned, "end"
        if max_scan is not None and scanned >= max_scan:
            return chosen, scanned, "max_scan"
        if until is not None and clock() >= until:
            return chosen, scanned, "time"
        like = similarity(items[at], best)
        if (like < threshold - 1e-12) if guard == "intent" else (like > threshold + 1e-12):
            return chosen, scanned, "guard"
        gains = []
        for pos, c in enumerate(chosen):
            rest = chosen[:pos] + chosen[pos + 1 :]
            if diversity == "min":
                gain = set_diversity([items[i] for i in [*rest, at]], "min") - set_diversity([items[i] for i in chosen], "min")
            else:
                gain = sum(similarity(items[i], items[c]) - similarity(items[i], items[at]) for i in rest)
            if gain > 1e-12:
                gains.append((round(gain, 9), -pos))
                if swap == "first":
                    break
        if gains:
            chosen[-max(gains)[1]] = at
        scanned += 1
        at += 1


def highlight(ranked: DataFrame, pois: DataFrame, k_primes: DataFrame, attrs: list[str], params: Params = Params()) -> DataFrame:
    """Highlights of every region from its ranked points (session_id, roi_id, poi_id, relevance, rank).

    The scan goes on to the guard or the end of the list.  Where max_scan is given, only the first
    k' + max_scan points of a region are joined and shipped to the kernel.
    """
    p = params
    rows = ranked.join(k_primes.select("session_id", "roi_id", "k_prime"), ["session_id", "roi_id"])
    if p.max_scan is not None:
        rows = rows.where(F.col("rank") <= F.least(F.col("k_prime"), F.lit(p.k)) + p.max_scan)
    rows = rows.where("k_prime > 0").join(pois.select("poi_id", F.array(*attrs).alias("_a")), "poi_id")

    def kernel(table: pa.Table) -> pa.Table:
        t = table.sort_by([("roi_id", "ascending"), ("rank", "ascending")]).to_pylist()
        out, i = [], 0
        while i < len(t):
            j = i
            while j < len(t) and t[j]["roi_id"] == t[i]["roi_id"]:
                j += 1
            group = t[i:j]
            chosen, scanned, why = swap_scan([tuple(r["_a"]) for r in group], group[0]["k_prime"], p.threshold, p.guard, p.swap, p.diversity, p.max_scan, p.time_limit_ms)
            for n, c in enumerate(sorted(chosen), 1):
                r = group[c]
                out.append((r["session_id"], r["roi_id"], n, r["poi_id"], r["relevance"], r["k_prime"], scanned, why))
            i = j
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int32(), pa.int32(), pa.string())
        names = ("session_id", "roi_id", "rank", "poi_id", "relevance", "k_prime", "scanned", "stop_reason")
        cols = list(zip(*out, strict=True)) or [()] * len(names)
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], list(names))

    return rows.groupBy("session_id").applyInArrow(kernel, SCHEMA)


def dedup_across_rois(highlights: DataFrame) -> DataFrame:
    """Each POI once a session, in its region of least roi_id."""
    first = F.min("roi_id").alias("_r")
    keep = highlights.groupBy("session_id", "poi_id").agg(first)
    return highlights.join(keep, ["session_id", "poi_id"]).where("roi_id = _r").select(*highlights.columns)
