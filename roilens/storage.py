"""Tables that outlive executors: lineage is cut by Parquet in the folder all executors share."""

from __future__ import annotations

import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark's own reader whatever store the path names."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder; one is made only where a session has none (tests)."""
    ctx = spark.sparkContext
    if ctx.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not ctx.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        ctx.setCheckpointDir(named or "file://" + tempfile.mkdtemp(prefix="roilens-shared-"))
    return ctx.getCheckpointDir()


def written(df: DataFrame, label: str) -> DataFrame:
    """``df`` written as Parquet in the shared folder and read back."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _tables.add(out)
    return out


_tables: weakref.WeakSet[DataFrame] = weakref.WeakSet()


def stored(df: DataFrame, label: str = "table") -> DataFrame:
    """``df`` itself if ``written`` returned it, else ``df`` written: for plans that read it more than once."""
    return df if df in _tables else written(df, label)
