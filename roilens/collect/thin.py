"""Thinning: at most one point per gap, so that redundant signals never reach a shuffle."""

from __future__ import annotations


import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def grid(moves: DataFrame, eps_ms: int = 100) -> DataFrame:
    """The first move of each cell of a clock grid.

    ``min_by`` over (session, cell) combines on the map side: what is shuffled is bounded by session
    time over eps, however fast a device reports.
    """
    rest = [c for c in moves.columns if c not in ("session_id",)]
    first = F.min(F.struct("t_ms", "event_id", *(c for c in rest if c not in ("t_ms", "event_id"))))
    cells = moves.groupBy("session_id", F.expr(f"t_ms div {int(eps_ms)}").alias("_cell")).agg(first.alias("_m"))
    return cells.select(*(F.col("session_id") if c == "session_id" else F.col(f"_m.{c}").alias(c) for c in moves.columns))


def refractory(moves: DataFrame, eps_ms: int = 100) -> DataFrame:
    """Each kept move is the first at least eps after the last kept one: a fold in time order.

    The fold needs a session's moves together; they are cut to one per millisecond first, which the
    fold would drop anyway, so a session's group is bounded by its duration.
    """
    slim = grid(moves, 1)
    columns, schema = slim.columns, slim.schema

    def fold(table: pa.Table) -> pa.Table:
        ordered = table.sort_by([("t_ms", "ascending"), ("event_id", "ascending")])
        keep, last = [], None
        for i, t in enumerate(ordered["t_ms"].to_pylist()):
            if last is None or t >= last + eps_ms:
                keep.append(i)
                last = t
        return ordered.take(pa.array(keep, pa.int64())).select(columns)

    return slim.groupBy("session_id").applyInArrow(fold, schema)


def drop_repeats(moves: DataFrame) -> DataFrame:
    """Without moves that repeat the pixel of the one before in their session."""
    w = W.partitionBy("session_id").orderBy("t_ms", "event_id")
    same = (F.lag("x").over(w) == F.col("x")) & (F.lag("y").over(w) == F.col("y"))
    return moves.withColumn("_same", F.coalesce(same, F.lit(False))).where("not _same").drop("_same")


def thin(moves: DataFrame, how: str = "grid", eps_ms: int = 100) -> DataFrame:
    return {"grid": grid, "refractory": refractory}[how](moves, eps_ms)
