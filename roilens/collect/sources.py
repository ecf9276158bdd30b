"""Signals as moves (session_id, event_id, t_ms, x, y, signal), read from the given tables.

Screen coordinates are pixels with the origin in the middle of the layer.  The carriers are fixed
integer arithmetic, so that any engine derives the same pixels (SURVEY 1.4).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import table

# The five hot spots of the carriers, in order of event type.
ANCHOR_X = (-500, -250, 0, 250, 500)
ANCHOR_Y = (-200, 150, -100, 200, 0)
TYPES = ("click", "error", "purchase", "signup", "view")
NOISE_FROM = 120.0


def at_index(values: tuple[int, ...], index: Column) -> Column:
    """values[index] as a chain of conditions, which stays inside generated code."""
    out = F.lit(values[-1]).cast("long")
    for i in range(len(values) - 2, -1, -1):
        out = F.when(index == i, F.lit(values[i]).cast("long")).otherwise(out)
    return out


def micros_since_2024(ts: str = "ts") -> Column:
    """Microseconds since 2024-01-01 of a time without zone, whatever zone the session has."""
    return F.expr(f"cast(cast(cast({ts} as timestamp_ntz) - timestamp_ntz'2024-01-01 00:00:00' as interval second) as decimal(20,6)) * 1000000").cast("long")


def moves(spark: SparkSession, sf_dir: str, kind: str = "hover", users_per_session: int = 8, spots: int | None = None) -> DataFrame:
    """Carrier M: events as pointer moves, with the planted truth (true_spot, true_noise).

    ``kind`` 'drift' moves from one hot spot to the next every six seconds; 'still' does so without
    jitter.  ``spots`` keeps only moves around that hot spot (and no noise).
    """
    e = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    e = e.withColumn("us", micros_since_2024()).withColumn("t_ms", F.expr("us div 86400000"))
    e = e.withColumn("session_id", F.expr(f"user_id div {users_per_session}")).withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    ty = F.lit(len(TYPES) - 1)
    for i, name in enumerate(TYPES[:-1]):
        ty = F.when(F.col("event_type") == name, i).otherwise(ty)
    if kind in ("drift", "still"):
        ty = F.least(F.lit(4), F.expr("t_ms div 6000")).cast("int")
    e = e.withColumn("ty", ty.cast("int"))
    noise = F.col("value") >= NOISE_FROM
    jitter = kind != "still"
    x = at_index(ANCHOR_X, F.col("ty"))
    y = at_index(ANCHOR_Y, F.col("ty"))
    if jitter:
        x = x + (F.expr("k % 10") - 5) * 8 + F.expr("session_id % 4") * 7
        y = y + (F.expr("k div 10") - 5) * 8 + F.expr("session_id % 3") * 5
        x = F.when(noise, F.expr("(event_id * 7919) % 1600 - 800")).otherwise(x)
        y = F.when(noise, F.expr("(event_id * 104729) % 900 - 450")).otherwise(y)
    out = e.select("session_id", "event_id", "t_ms", x.cast("long").alias("x"), y.cast("long").alias("y"), F.lit("hover").alias("signal"), F.col("ty").alias("true_spot"), noise.alias("true_noise"))
    return out if spots is None else out.where((F.col("true_spot") == spots) & ~F.col("true_noise"))


def clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Carrier C: decision-making feedback (session_id, poi_id, t_ms), lines of orders as picks."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    t = F.expr("cast(datediff(cast(o_orderdate as date), date'1992-01-01') as bigint)") * 10
    return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select(F.expr("o_custkey div 8").alias("session_id"), F.col("l_partkey").alias("poi_id"), t.alias("t_ms"))


def tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Carrier Tr: a user's events in time order as one trajectory; value stands for altitude."""
    m = moves(spark, sf_dir).select("event_id", "t_ms", "x", "y")
    e = table(spark, sf_dir, "events").select(F.col("event_id").alias("_id"), F.col("user_id").alias("track_id"), F.col("value").alias("alt"))
    return e.join(m, F.col("_id") == F.col("event_id")).select("track_id", "event_id", "t_ms", "x", "y", "alt")


def voice(spark: SparkSession, sf_dir: str, per_session: int = 8, apart_ms: int = 150) -> DataFrame:
    """Turns of conversations as voice commands about a place: so many conversations a session, that far apart."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.length("text").alias("n"))
    said = c.where("role = 'user'").select(
        F.expr(f"conv_id div {per_session}").alias("session_id"), (F.col("conv_id") * 1000 + F.col("turn")).alias("event_id"), (F.col("turn") * 3000 + F.col("conv_id") % per_session * apart_ms).alias("t_ms"), "n", "conv_id", "turn"
    )
    spot = F.col("n") % 5
    return said.select("session_id", "event_id", "t_ms", (at_index(ANCHOR_X, spot) + F.col("turn") * 5).alias("x"), (at_index(ANCHOR_Y, spot) + F.col("conv_id") % 7 * 4).alias("y"), F.lit("voice").alias("signal"))


#: How a typed signal's columns become a move; each maps a name to an expression.
SIGNALS: dict[str, dict[str, str]] = {
    "hover": {"x": "x", "y": "y"},
    "gaze": {"x": "gaze_x", "y": "gaze_y"},
    "scroll": {"x": "x", "y": "y + delta_y"},
    "pinch": {"x": "(x1 + x2) div 2", "y": "(y1 + y2) div 2"},
    "zoom": {"x": "centre_x", "y": "centre_y"},
    "voice": {"x": "x", "y": "y"},
    "detail": {"x": "item_x", "y": "item_y"},
}


def from_signal(df: DataFrame, kind: str, mapping: dict[str, str] | None = None) -> DataFrame:
    """Rows of any signal with session_id, event_id and t_ms as moves, by a registered or given mapping."""
    how = mapping or SIGNALS[kind]
    return df.select("session_id", "event_id", "t_ms", F.expr(how["x"]).cast("long").alias("x"), F.expr(how["y"]).cast("long").alias("y"), F.lit(kind).alias("signal"))


def register_signal(kind: str, mapping: dict[str, str]) -> None:
    SIGNALS[kind] = mapping


Carrier = Callable[[SparkSession, str], DataFrame]
