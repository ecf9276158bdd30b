"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark's own reader whatever store the path names."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: the session's checkpoint folder.

    A cluster names it in ``spark.checkpoint.dir``.  Only where a session has none (tests on one
    machine) is a folder made here.
    """
    ctx = spark.sparkContext
    named = ctx.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if named is None:
        if not ctx.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="roilens-shared-")
    if ctx.getCheckpointDir() is None:
        ctx.setCheckpointDir(named)
    return ctx.getCheckpointDir()


def written(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage of ``df``: write it as Parquet in the shared folder and read it back.

    The table outlives lost executors, which cached blocks and local checkpoints do not.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fold(doc_id: str | Column, modulus: int) -> Column:
    """crc32 of the id as text, modulo ``modulus``; null ids fall in fold 0."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.pmod(F.coalesce(F.crc32(c.cast("string").cast("binary")), F.lit(0)), F.lit(modulus))


def unit_hash(*cols: str | Column, seed: int = 0) -> Column:
    """A pseudo-random number in [0, 1) from the columns' values: the same in every run and plan."""
    h = F.xxhash64(F.lit(seed), *cols)
    return F.shiftrightunsigned(h, 11).cast("double") / F.lit(float(1 << 53))


def labelled_sample(
    docs: DataFrame, labels: DataFrame, label: str, keep: Column, bound: int, seed: int
) -> DataFrame:
    """(doc_id, text, label) of about ``bound`` labelled rows at most.

    ``keep`` says which rows of ``labels`` may teach (the training folds).  Rows are taken by a
    hash threshold, so the choice does not depend on partitions; ``bound`` is in expectation.  The
    chosen ids are that many longs, a proven size, and are broadcast.
    """
    usable = labels.where(keep & F.col("doc_id").isNotNull() & F.col(label).isNotNull())
    n = usable.count()
    share = min(1.0, bound / n) if n else 0.0
    picked = usable.where(unit_hash("doc_id", seed=seed) < share).select(
        F.col("doc_id").alias("_id"), F.col(label).cast("int").alias("_label")
    )
    ids = picked.groupBy("_id").agg(F.max("_label").alias("_label"))
    return docs.join(F.broadcast(ids), docs["doc_id"] == ids["_id"]).select("doc_id", "text", "_label")


def cpu_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))

