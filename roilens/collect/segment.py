"""Segmentation of a session's moves: boundary flags, then a prefix count of flags.

A flag says that a row ends its segment; a row's segment is one more than the number of flags strictly
before it, so the row that triggers a change belongs to the segment it closes.  All of it is window
functions over one partitioning by session, sorted once; segments are numbered from 1 without gaps.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..params import Params
from . import drift

ORDER = ("t_ms", "event_id")


def _session():
    return W.partitionBy("session_id").orderBy(*ORDER)


def fixed_length(moves: DataFrame, length_ms: int | None = None, g: int | None = None, horizon_ms: int = 30_000) -> Column:
    """Flags where the next move lies in another slice of time; slices start at time zero."""
    slice_ = F.expr(f"t_ms div {int(length_ms)}") if length_ms else F.least(F.lit(g - 1), F.expr(f"(t_ms * {int(g)}) div {int(horizon_ms)}"))
    nxt = F.lead(slice_).over(_session())
    return F.coalesce(nxt != slice_, F.lit(False))


def idle(moves: DataFrame, tau_ms: int = 300, evidence: str = "either") -> Column:
    """Flags by an idle pointer: no signal for tau, or the same pixel for tau, or either.

    ``moves`` must have the columns of ``with_stints``.  'gap' ends a segment with the last move before the silence; 'still' with the move at which the
    pixel has been the same for tau, once per stint.
    """
    w = _session()
    gap = F.coalesce(F.lead("t_ms").over(w) - F.col("t_ms") >= tau_ms, F.lit(False))
    if evidence == "gap":
        return gap
    reached = F.col("t_ms") - F.col("_stint") >= tau_ms
    before = F.coalesce(F.lag("t_ms").over(w) - F.lag("_stint").over(w) >= tau_ms, F.lit(False)) & ~F.col("_moved")
    still = reached & ~before
    return still if evidence == "still" else gap | still


def with_stints(moves: DataFrame) -> DataFrame:
    """moves with _moved (pixel differs from the one before) and _stint (when the pixel was reached)."""
    w = _session()
    moved = F.coalesce((F.lag("x").over(w) != F.col("x")) | (F.lag("y").over(w) != F.col("y")), F.lit(True))
    out = moves.withColumn("_moved", moved)
    return out.withColumn("_stint", F.max(F.when(F.col("_moved"), F.col("t_ms"))).over(w.rowsBetween(W.unboundedPreceding, W.currentRow)))


def assign(flagged: DataFrame, keep_open: bool = True) -> DataFrame:
    """``seg`` from the column ``is_end``; ``keep_open=False`` drops the last segment if nothing closed it."""
    before = _session().rowsBetween(W.unboundedPreceding, -1)
    out = flagged.withColumn("seg", (F.coalesce(F.sum(F.col("is_end").cast("int")).over(before), F.lit(0)) + 1).cast("int"))
    if not keep_open:
        closed = F.max(F.when(F.col("is_end"), F.col("seg"))).over(W.partitionBy("session_id"))
        out = out.withColumn("_closed", closed).where(F.col("seg") <= F.col("_closed")).drop("_closed")
    return out.drop("is_end")


def segment(moves: DataFrame, params: Params = Params()) -> DataFrame:
    """moves with ``seg``, by the strategy of ``params``."""
    p, kept = params, moves.columns
    if p.strategy == "fixed":
        flagged = moves.withColumn("is_end", fixed_length(moves, p.length_ms, p.g, p.horizon_ms))
    elif p.strategy == "idle":
        flagged = with_stints(moves)
        flagged = flagged.withColumn("is_end", idle(flagged, p.tau_ms, p.evidence))
    else:
        flagged = drift.flags(moves, p)
    return assign(flagged, p.keep_open).select(*kept, "seg")


def g_from_density(mean_per_leaf: float) -> int:
    """Number of fixed-length segments from the mean number of POIs in a non-empty quadtree leaf."""
    return int(min(12, max(2, round(mean_per_leaf**0.5))))


def g_from_leaves(leaves: DataFrame) -> int:
    """``g_from_density`` of a quadtree's leaves; the least number where there is none."""
    return g_from_density(leaves.agg(F.avg("n")).first()[0] or 0.0)


def summary(segmented: DataFrame) -> DataFrame:
    """(session_id, seg, t_start, t_end, n)."""
    return segmented.groupBy("session_id", "seg").agg(F.min("t_ms").alias("t_start"), F.max("t_ms").alias("t_end"), F.count("*").alias("n"))
