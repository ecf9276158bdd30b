"""The feedback vector, sparse by facet: increments only add up, softmax is a view of the raw sums.

Because raw feedback only grows, the vector after region i is a prefix sum over regions, and the
sequential update is one window instead of a loop.  The literal reading that replaces the vector by
its softmax after each update is kept as ``sequential_state``.
"""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def increments(matched: DataFrame, facets: DataFrame, delta: float = 0.05, per: str = "point") -> DataFrame:
    """(session_id, roi_id, attr, val, inc): delta a matching point, or once a value."""
    return increments_of(matched.join(facets, "poi_id").groupBy("session_id", "roi_id", "attr", "val").agg(F.count("*").alias("n")), delta, per)


def increments_of(counts: DataFrame, delta: float = 0.05, per: str = "point") -> DataFrame:
    """``increments`` from the number of a region's points by facet (``inside.counts``)."""
    inc = F.col("n") * F.lit(delta) if per == "point" else F.lit(delta)
    return counts.where("attr is not null").select("session_id", "roi_id", "attr", "val", inc.alias("inc"))


def batch(matched: DataFrame, facets: DataFrame, delta: float = 0.05, per: str = "point", before: DataFrame | None = None) -> DataFrame:
    """(session_id, attr, val, raw) after all regions at once, on top of ``before``."""
    return added(increments(matched, facets, delta, per), before)


def added(increments: DataFrame, before: DataFrame | None = None) -> DataFrame:
    """(session_id, attr, val, raw): all increments, on top of ``before``."""
    inc = increments.select("session_id", "attr", "val", F.col("inc").alias("raw"))
    return total(inc if before is None else inc.unionByName(before.select("session_id", "attr", "val", "raw")))


def total(rows: DataFrame) -> DataFrame:
    return rows.groupBy("session_id", "attr", "val").agg(F.sum("raw").alias("raw"))


def sequential(matched: DataFrame, facets: DataFrame, delta: float = 0.05, per: str = "point", before: DataFrame | None = None) -> DataFrame:
    """(session_id, roi_id, attr, val, raw): the vector after each region, in order of roi_id.

    Dense over a session's regions and the cells touched by then or later; cells not touched yet have
    raw 0, so readers of the vector after region i need no other row.
    """
    return running(increments(matched, facets, delta, per), matched.select("session_id", "roi_id").distinct(), before)


def running(inc: DataFrame, regions: DataFrame, before: DataFrame | None = None) -> DataFrame:
    """``sequential`` from increments and the regions (session_id, roi_id) that have points."""
    cells = inc.select("session_id", "attr", "val")
    if before is not None:
        cells = cells.unionByName(before.select("session_id", "attr", "val"))
    dense = regions.join(cells.distinct(), "session_id")
    run = W.partitionBy("session_id", "attr", "val").orderBy("roi_id").rowsBetween(W.unboundedPreceding, W.currentRow)
    out = dense.join(inc, ["session_id", "roi_id", "attr", "val"], "left")
    raw = F.sum(F.coalesce("inc", F.lit(0.0))).over(run)
    if before is not None:
        out = out.join(before.select("session_id", "attr", "val", F.col("raw").alias("_raw0")), ["session_id", "attr", "val"], "left")
        raw = raw + F.coalesce("_raw0", F.lit(0.0))
    return out.select("session_id", "roi_id", "attr", "val", raw.alias("raw"))


def softmax(vector: DataFrame, n_cells: int | Column, keys: tuple[str, ...] = ("session_id",)) -> DataFrame:
    """vector with weight, and per vector w0 (weight of an untouched cell) and norm.

    The largest raw value is taken off before exponentials; untouched cells enter by their number, so
    the vector stays sparse.
    """
    f = F.lit(n_cells) if isinstance(n_cells, int) else n_cells
    w = W.partitionBy(*keys)
    top = F.greatest(F.max("raw").over(w), F.lit(0.0))
    out = vector.withColumn("_top", top).withColumn("_e", F.exp(F.col("raw") - F.col("_top")))
    rest = F.greatest(f - F.count("*").over(w), F.lit(0))
    out = out.withColumn("_z", F.sum("_e").over(w) + rest * F.exp(-F.col("_top"))).withColumn("_rest", rest)
    out = out.withColumn("weight", F.col("_e") / F.col("_z")).withColumn("w0", F.exp(-F.col("_top")) / F.col("_z"))
    out = out.withColumn("norm", F.sqrt(F.sum(F.col("weight") * F.col("weight")).over(w) + F.col("_rest") * F.col("w0") * F.col("w0")))
    return out.drop("_top", "_e", "_z", "_rest")


def plain(vector: DataFrame, keys: tuple[str, ...] = ("session_id",)) -> DataFrame:
    """The raw vector in the shape of ``softmax``: no weight for untouched cells."""
    w = W.partitionBy(*keys)
    return vector.withColumn("weight", F.col("raw")).withColumn("w0", F.lit(0.0)).withColumn("norm", F.sqrt(F.sum(F.col("raw") * F.col("raw")).over(w)))


def sequential_state(matched: DataFrame, facets: DataFrame, cells: DataFrame, delta: float = 0.05, per: str = "point") -> DataFrame:
    """(session_id, roi_id, attr, val, raw): the literal state, replaced by its softmax after each region.

    A true fold, one session at a time; its input is the session's increments, not its points.
    """
    return folded(increments(matched, facets, delta, per), cells)


def folded(increments: DataFrame, cells: DataFrame) -> DataFrame:
    """``sequential_state`` from increments."""
    all_cells = [(r.attr, r.val) for r in cells.select("attr", "val").orderBy("attr", "val").collect()]

    def fold(table: pa.Table) -> pa.Table:
        t = table.sort_by([("roi_id", "ascending")]).to_pylist()
        state = dict.fromkeys(all_cells, 0.0)
        out, i = [], 0
        while i < len(t):
            roi = t[i]["roi_id"]
            while i < len(t) and t[i]["roi_id"] == roi:
                state[t[i]["attr"], t[i]["val"]] += t[i]["inc"]
                i += 1
            top = max(state.values())
            e = {c: math.exp(v - top) for c, v in state.items()}
            z = sum(e.values())
            state = {c: v / z for c, v in e.items()}
            out += [(t[0]["session_id"], roi, a, v, x) for (a, v), x in state.items()]
        cols = list(zip(*out, strict=True))
        return pa.table([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), pa.array(cols[2]), pa.array(cols[3]), pa.array(cols[4], pa.float64())], ["session_id", "roi_id", "attr", "val", "raw"])

    inc = increments.withColumn("roi_id", F.col("roi_id").cast("int"))
    return inc.groupBy("session_id").applyInArrow(fold, "session_id long, roi_id int, attr string, val string, raw double")


def with_clicks(raw: DataFrame, clicks: DataFrame, facets: DataFrame, delta_click: float) -> DataFrame:
    """Feedback with decision-making signals added: each click counts ``delta_click`` for its POI's cells."""
    more = clicks.join(facets, "poi_id").groupBy("session_id", "attr", "val").agg((F.count("*") * F.lit(delta_click)).alias("raw"))
    return total(raw.select("session_id", "attr", "val", "raw").unionByName(more))


def decayed(increments_by_round: DataFrame, now: int, rate: float) -> DataFrame:
    """(session_id, attr, val, raw) with increments (.., round, inc) fading by exp(-rate * age)."""
    faded = F.col("inc") * F.exp(-F.lit(rate) * (F.lit(now) - F.col("round")))
    return increments_by_round.groupBy("session_id", "attr", "val").agg(F.sum(faded).alias("raw"))


def explain(vector: DataFrame, top: int = 5, by: str = "raw") -> DataFrame:
    """(session_id, rank, attr, val, value): a session's strongest facets, in plain text."""
    rank = F.row_number().over(W.partitionBy("session_id").orderBy(F.col(by).desc(), "attr", "val"))
    return vector.withColumn("rank", rank).where(F.col("rank") <= top).select("session_id", "rank", "attr", "val", F.col(by).alias("value"))
