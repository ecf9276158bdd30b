"""Drift detectors for the dynamic segmentation: three published kinds, none claimed to be another's.

'tiered': mean shift between the rows before and from a row on, at several nested widths; a boundary
needs all tiers to agree and to be the sharpest nearby.  'interp': error of interpolating a row from
its neighbours.  'cusum': cumulative deviation of step length, reset at each boundary.
"""

from __future__ import annotations

from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

from ..params import Params


def _session():
    return W.partitionBy("session_id").orderBy("t_ms", "event_id")


def _tier(w: int) -> Column:
    """Distance of the mean points before and from a row on, over the pooled spread; 0 without full frames."""
    back, ahead = _session().rowsBetween(-w, -1), _session().rowsBetween(0, w - 1)
    full = (F.count("x").over(back) == w) & (F.count("x").over(ahead) == w)
    dx, dy = F.avg("x").over(ahead) - F.avg("x").over(back), F.avg("y").over(ahead) - F.avg("y").over(back)
    spread = sum((F.var_pop(c).over(f) for c in ("x", "y") for f in (back, ahead)), F.lit(0.0)) / 2 + 1
    return F.when(full, F.round(F.sqrt(dx * dx + dy * dy) / F.sqrt(spread), 9)).otherwise(0.0)


def tiered(moves: DataFrame, widths: tuple[int, ...] = (4, 8, 16), threshold: float = 1.0) -> DataFrame:
    """``is_end`` on the row before each boundary."""
    scored = reduce(lambda d, w: d.withColumn(f"_t{w}", _tier(w)), widths, moves)
    least = F.least(*(F.col(f"_t{w}") for w in widths)) if len(widths) > 1 else F.col(f"_t{widths[0]}")
    scored = scored.withColumn("_s", least)
    r = min(widths)
    near, earlier = _session().rowsBetween(-r, r), _session().rowsBetween(-r, -1)
    sharp = (F.col("_s") >= threshold) & (F.col("_s") == F.max("_s").over(near)) & (F.coalesce(F.max("_s").over(earlier), F.lit(-1.0)) < F.col("_s"))
    scored = scored.withColumn("_begin", sharp)
    return scored.withColumn("is_end", F.coalesce(F.lead("_begin").over(_session()), F.lit(False)))


def interp(moves: DataFrame, width: int = 4, factor: float = 2.0) -> DataFrame:
    """``is_end`` where interpolation from the rows ``width`` away errs by over mean + factor * std of the session."""
    w, whole = _session(), W.partitionBy("session_id")
    err = F.sqrt(sum(((F.lag(c, width).over(w) + F.lead(c, width).over(w)) / 2 - F.col(c)) ** 2 for c in ("x", "y")))
    scored = moves.withColumn("_e", F.coalesce(F.round(err, 9), F.lit(0.0)))
    scored = scored.withColumn("_bar", F.round(F.avg("_e").over(whole) + factor * F.stddev_pop("_e").over(whole), 9))
    near, earlier = w.rowsBetween(-width, width), w.rowsBetween(-width, -1)
    top = (F.col("_e") > F.col("_bar")) & (F.col("_e") == F.max("_e").over(near)) & (F.coalesce(F.max("_e").over(earlier), F.lit(-1.0)) < F.col("_e"))
    return scored.withColumn("is_end", top)


def cusum(moves: DataFrame, slack: float = 1.0, bar: float = 6.0) -> DataFrame:
    """``is_end`` where the one-sided cumulative deviation of step length, in session deviations, passes ``bar``."""
    schema = T.StructType([*moves.schema, T.StructField("is_end", T.BooleanType())])

    def fold(table: pa.Table) -> pa.Table:
        t = table.sort_by([("t_ms", "ascending"), ("event_id", "ascending")])
        x, y = t["x"].to_pylist(), t["y"].to_pylist()
        step = [0.0] + [((a - b) ** 2 + (c - d) ** 2) ** 0.5 for a, b, c, d in zip(x[1:], x, y[1:], y, strict=False)]
        mean = sum(step) / len(step)
        dev = (sum((s - mean) ** 2 for s in step) / len(step)) ** 0.5 or 1.0
        out, total = [], 0.0
        for s in step:
            total = max(0.0, total + (s - mean) / dev - slack)
            out.append(total > bar)
            total = 0.0 if out[-1] else total
        return t.append_column("is_end", pa.array(out, pa.bool_()))

    return moves.groupBy("session_id").applyInArrow(fold, schema)


def flags(moves: DataFrame, p: Params) -> DataFrame:
    if p.detector == "tiered":
        return tiered(moves, p.widths, p.drift_threshold)
    return interp(moves, min(p.widths)) if p.detector == "interp" else cusum(moves)
