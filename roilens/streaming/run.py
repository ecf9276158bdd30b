"""The collecting stage as Structured Streaming, hulls of closed segments, and a loop that mines and suggests per micro-batch.

Event time is the carrier's timestamp taken as UTC.  Results are compared with batch runs up to the
watermark: in append mode a window comes out once the watermark passes its end.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.window import Window as W

from ..collect.sources import micros_since_2024
from ..geo import kernels, polygon
from ..mine import cluster
from ..params import Params
from ..storage import shared_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
EPOCH_2024 = 1_704_067_200_000_000  # microseconds
SESSION_MS = 86_400_000  # event-time microseconds that stand for a millisecond of a session


def source(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """Signals as a stream: event_id, session_id, user_id, at (event time), event_type, value."""
    raw = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", files_per_trigger).parquet(sf_dir)
    return timed(raw)


def timed(raw: DataFrame) -> DataFrame:
    at = F.timestamp_micros(micros_since_2024() + F.lit(EPOCH_2024))
    return raw.select("event_id", F.expr("user_id div 8").alias("session_id"), "user_id", at.alias("at"), "event_type", "value")


def drain(stream: DataFrame, mode: str = "append", label: str = "stream", seen: dict | None = None) -> DataFrame:
    """Run a stream over all there is now into Parquet in the shared folder; returns what came out.

    In complete mode the last batch is the result; in update mode all emitted versions are kept with
    their ``batch``.  ``seen`` gets the number of rows that came after the watermark (``late``).
    """
    spark = stream.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"

    came = []

    def put(df: DataFrame, batch: int) -> None:
        out = df.withColumn("batch", F.lit(batch)) if mode == "update" else df
        out.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{path}/out")
        came.append(batch)

    query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    if seen is not None:
        seen["late"] = sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])
    schema = stream.schema.add("batch", "int") if mode == "update" else stream.schema
    return spark.read.schema(schema).parquet(f"{path}/out") if came else spark.createDataFrame([], schema)


def tumbling(stream: DataFrame, length: str = "1 day") -> DataFrame:
    return stream.groupBy("session_id", F.window("at", length).alias("w")).agg(F.count("*").alias("n")).select("session_id", F.unix_micros("w.start").alias("start_us"), "n")


def sliding(stream: DataFrame, length: str = "2 days", step: str = "1 day") -> DataFrame:
    """Density trend: moves in overlapping windows."""
    return stream.groupBy("session_id", F.window("at", length, step).alias("w")).agg(F.count("*").alias("n")).select("session_id", F.unix_micros("w.start").alias("start_us"), "n")


def idle_segments(stream: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Segments that end with a silence, by session windows."""
    w = stream.withWatermark("at", late).groupBy("session_id", F.session_window("at", gap).alias("w"))
    return w.agg(F.count("*").alias("n"), F.min("at").alias("first"), F.max("at").alias("last")).select("session_id", F.unix_micros("first").alias("first_us"), F.unix_micros("last").alias("last_us"), "n")


def thinned(stream: DataFrame, eps_ms: int = 100, late: str = "1 hour") -> DataFrame:
    """The first signal of each cell of the clock grid."""
    seconds = eps_ms * SESSION_MS // 1_000_000
    g = stream.withWatermark("at", late).groupBy("session_id", F.window("at", f"{seconds} seconds").alias("w"))
    return g.agg(F.min(F.struct("at", "event_id")).alias("m")).select("session_id", F.col("m.event_id").alias("event_id"), F.unix_micros("m.at").alias("at_us"))


def deduplicated(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"])


def with_static(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    return stream.join(static, key)


def hover_then_purchase(stream: DataFrame, within: str = "2 hours", late: str = "1 hour") -> DataFrame:
    """Views followed by a purchase of the same user within a time: a join of two streams by interval."""
    a = stream.where("event_type = 'view'").withWatermark("at", late).select(F.col("user_id").alias("u"), F.col("event_id").alias("view_id"), F.col("at").alias("seen"))
    b = stream.where("event_type = 'purchase'").withWatermark("at", late).select(F.col("user_id").alias("v"), F.col("event_id").alias("purchase_id"), F.col("at").alias("bought"))
    return a.join(b, F.expr(f"u = v and bought >= seen and bought <= seen + interval {within}")).select(F.col("u").alias("user_id"), "view_id", "purchase_id")


def drift_segments(stream: DataFrame, width: int = 8, threshold: float = 1.0, late: str = "1 hour") -> DataFrame:
    """(session_id, seg, n, first_us, last_us): segments ended by a shift of the mean of ``value``, kept in state.

    The state is the last 2 * width values and the open segment's counters, whatever the stream's length.
    """
    state = "values string, seg int, n long, first_us long, last_us long"
    out = "session_id long, seg int, n long, first_us long, last_us long"

    def step(key: tuple, frames: Iterator[pd.DataFrame], s: GroupState) -> Iterator[pd.DataFrame]:
        text, seg, n, first, last = s.get if s.exists else ("", 1, 0, 0, 0)
        values = [float(v) for v in text.split(",")] if text else []
        closed = []
        rows = pd.concat(list(frames)).sort_values(["us", "event_id"]) if not s.hasTimedOut else pd.DataFrame()
        for us, v in zip(rows.get("us", []), rows.get("value", []), strict=True):
            values = (values + [float(v)])[-2 * width :]
            n, first, last = n + 1, first or int(us), int(us)
            if len(values) == 2 * width:
                a, b = values[:width], values[width:]
                ma, mb = sum(a) / width, sum(b) / width
                spread = (sum((x - ma) ** 2 for x in a) + sum((x - mb) ** 2 for x in b)) / (2 * width) + 1
                if abs(ma - mb) / spread**0.5 >= threshold:
                    closed.append((key[0], seg, n, first, last))
                    values, seg, n, first = [], seg + 1, 0, 0
        s.update((",".join(map(repr, values)), seg, n, first, last))
        yield pd.DataFrame(closed, columns=["session_id", "seg", "n", "first_us", "last_us"])

    rows = stream.withWatermark("at", late).select("session_id", "event_id", "at", F.unix_micros("at").alias("us"), "value")
    return rows.groupBy("session_id").applyInPandasWithState(step, out, state, "append", GroupStateTimeout.NoTimeout)


def closed_hulls(stream: DataFrame, gap: str = "6 hours", late: str = "1 hour", params: Params = Params()) -> DataFrame:
    """(session_id, first_us, last_us, cluster_id, n, poly, area): hulls of the clusters of every closed segment.

    A segment ends with a silence of ``gap``; it comes out once the watermark has passed that silence, so
    the state holds open segments only.  Rows need session_id, event_id, at, x, y.  The same plan runs on a
    table, where all segments are closed.
    """
    p = params
    point = F.struct("event_id", F.unix_micros("at").alias("us"), F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"))
    segments = stream.withWatermark("at", late).groupBy("session_id", F.session_window("at", gap).alias("w")).agg(F.collect_list(point).alias("points"))
    vertex = pa.struct([("x", pa.float64()), ("y", pa.float64())])
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(vertex)]
    names = ["session_id", "first_us", "last_us", "cluster_id", "n", "poly"]

    def hulls(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for session, points in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                e, us = (np.array([q[c] for q in points], np.int64) for c in ("event_id", "us"))
                x, y = (np.array([q[c] for q in points], float) for c in ("x", "y"))
                name, _ = cluster.dbscan_arrays(x, y, e, p.radius, p.min_pts, p.strict, p.count_self)
                for c in np.unique(name[name >= 0]).tolist():
                    at = np.flatnonzero(name == c)
                    ring = kernels.hull_chain(list(zip(x[at].tolist(), y[at].tolist(), strict=True)))
                    out.append((session, int(us.min()), int(us.max()), c, len(at), [{"x": vx, "y": vy} for vx, vy in ring]))
            cols = list(zip(*out, strict=True)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(cols, kinds, strict=True)], names)

    found = segments.select("session_id", "points").mapInArrow(hulls, f"session_id long, first_us long, last_us long, cluster_id long, n long, poly {polygon.POLYGON}")
    return found.withColumn("area", polygon.area(F.col("poly")))


def run(spark: SparkSession, stream_moves: DataFrame, pois: DataFrame, params: Params, on_round, store: str) -> None:
    """Per micro-batch of moves (session_id, event_id, t_ms, x, y, signal): append to the trail, then mine and suggest.

    Everything that outlives a batch is a table under ``store``, a folder that executors share, keyed by
    batch: ``moves``, and the ``feedback`` of the sessions a batch touched.  A batch overwrites its own part
    only and reads earlier parts, so one that is tried again, or comes after a restart, gives the same.
    Sessions that the batch touched are mined over their whole trail; a region that recurs over batches is
    found, and feedback is learnt anew from the trail, so it counts nothing twice.  What earlier batches
    taught stretches the regions.  ``on_round(batch, shot)`` gets each result.
    """
    from .. import pipeline

    root = store.rstrip("/")

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{root}/moves/batch={batch}")
        trail = spark.read.parquet(f"{root}/moves").where(F.col("batch") <= batch)
        touched = trail.where(F.col("batch") == batch).select("session_id").distinct()
        known = None
        if batch:
            earlier = spark.read.parquet(f"{root}/feedback").where(F.col("batch") < batch)
            newest = F.max("batch").over(W.partitionBy("session_id"))
            known = earlier.withColumn("_newest", newest).where("batch = _newest").drop("batch", "_newest")
        shot = pipeline.shot(trail.join(touched, "session_id", "left_semi").drop("batch"), pois, params.but(rounds_done=batch + 1), known, relearn=True)
        shot.feedback.write.mode("overwrite").parquet(f"{root}/feedback/batch={batch}")
        on_round(batch, shot)

    stream_moves.writeStream.foreachBatch(put).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
