"""SimHash near-duplicates by meet-in-the-middle ball hashing.

A fingerprint has 64 bits; bit i is set if it is set in over half of the XXH64 hashes of a text's
3-word shingles.  To link fingerprints that differ in at most ``RADIUS`` bits, every distinct
fingerprint emits itself and all variants within half that radius.  Two fingerprints within the
radius share a variant, and fingerprints that share one are within the radius: a shuffle on variants
finds every link and nothing else, which a bit count then verifies.  A variant's members number at
most its ball's size (65), so no group is large; inside it all members link to the least one, which
gives the same components as all pairs.  Copies share one fingerprint and are folded together before
anything is shuffled.

Null texts count as empty; texts without words have fingerprint zero and are linked like any other.
Null ids are never a component's id unless it has no other.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

from .common import written
from .components import components
from .substring import packed, with_texts
from .textscan import tidy

RADIUS = 2
SHINGLE = 3


def fingerprint(text: bytes, k: int = SHINGLE) -> int:
    """The 64-bit SimHash of one text's bytes.

    ``bytes.lower`` and ``bytes.split`` act on ASCII alone: A-Z, and space with 0x09-0x0D.
    """
    words = text.lower().split()
    if not words:
        return 0
    if len(words) < k:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[j:] for j in range(k)), strict=False))
    n = max(1, len(words) - k + 1)
    h = np.fromiter(map(xxhash.xxh64_intdigest, shingles, repeat(42)), np.uint64, n)
    ones = np.zeros(64, np.int64)
    for i in range(0, n, 1 << 16):
        ones += np.unpackbits(h[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, np.int64)
    return int.from_bytes(np.packbits(2 * ones > n, bitorder="little").tobytes(), "little")


def with_fingerprint(docs: DataFrame) -> DataFrame:
    """(doc_id, fp) of every row; fp is the fingerprint as a signed long."""
    base = docs.select("doc_id", "text")
    schema = T.StructType([base.schema["doc_id"], T.StructField("fp", T.LongType())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).fill_null("").cast(pa.binary())
            fps = np.fromiter((fingerprint(t.as_py()) for t in texts), np.uint64, len(texts))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    return base.mapInArrow(tidy(rows), schema)


def variants(radius: int) -> list[int]:
    """XOR masks (signed) of all bit patterns with at most ``radius // 2`` ones."""
    masks = [sum(1 << i for i in bits) for k in range(radius // 2 + 1) for bits in combinations(range(64), k)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def links(fps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Verified links (a, b) between distinct fingerprints that connect all within ``radius`` bits."""
    if radius % 2:
        raise ValueError("an even radius is wanted: its halves meet")
    masks = F.array(*(F.lit(m).cast("long") for m in variants(radius)))
    balls = fps.select("fp", F.explode(masks).alias("m")).select("fp", F.col("fp").bitwiseXOR(F.col("m")).alias("variant"))
    least = F.min("fp").over(W.partitionBy("variant"))
    met = balls.withColumn("a", least).where("fp != a").select("a", F.col("fp").alias("b")).distinct()
    return met.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius)


def classes(marked: DataFrame, radius: int = RADIUS) -> DataFrame:
    """(fp, component_id, root) of every distinct fingerprint of ``marked`` (doc_id, fp)."""
    firsts = written(marked.groupBy("fp").agg(F.min("doc_id").alias("first_id")), "fingerprints")
    roots = written(components(links(firsts.select("fp"), radius)), "roots")
    rooted = firsts.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    ids = rooted.groupBy(F.col("root").alias("of")).agg(F.min("first_id").alias("component_id"))
    return rooted.join(ids, F.col("root") == F.col("of")).select("fp", "component_id", "root")


def near_duplicates(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """doc_id, fingerprint (16 hex digits) and component_id of every row of ``docs``."""
    marked = written(with_fingerprint(docs), "marked")
    of = written(classes(marked, radius), "classes").select(F.col("fp").alias("of_fp"), "component_id")
    return marked.join(of, F.col("fp") == F.col("of_fp")).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """One row of ``docs`` for each component, with all columns: of its least doc_id, that with the least text.

    An id whose rows have different texts may head several components and leaves a row for each.  A
    component whose ids are all null leaves the row with the least text.
    """
    marked = written(with_fingerprint(docs), "marked")

    def fps(texts: pa.Array) -> np.ndarray:
        return np.array([fingerprint(t or b"") for t in texts.cast(pa.binary()).to_pylist()], np.uint64).view(np.int64)

    return one_each(docs, marked, written(classes(marked, radius), "classes"), fps)


def one_each(docs: DataFrame, marked: DataFrame, of: DataFrame, fps: Callable[[pa.Array], np.ndarray]) -> DataFrame:
    """``keep_one`` for the classes ``of`` (fp, component_id, root) of ``marked`` (doc_id, fp).

    ``fps`` gives the fp of each text again, which only rows without an id and rows of repeated ids need.
    """
    several = marked.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1")
    several = written(several.select(F.col("doc_id").alias("_several")), "several")
    keep = of.where("component_id is not null").select(F.col("component_id").alias("_keep")).distinct()
    keep = keep.join(several, F.col("_keep") == F.col("_several"), "left_anti")
    one = with_texts(packed(docs).join(keep, F.col("doc_id") == F.col("_keep"), "left_semi"), docs.schema)
    unclear = docs.where("doc_id is null").unionAll(docs.join(several, F.col("doc_id") == F.col("_several"), "left_semi"))
    schema = T.StructType([*docs.schema, T.StructField("_row_fp", T.LongType())])
    at = docs.columns.index("text")

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(fps(b.column(at)))], schema.names)

    heads = of.select(F.col("fp").alias("_fp"), F.col("component_id").alias("_head"), F.col("root").alias("_root"))
    rank = F.row_number().over(W.partitionBy("_root").orderBy(F.col("text").asc_nulls_last()))
    met = unclear.mapInArrow(tidy(mark), schema).join(heads, (F.col("_row_fp") == F.col("_fp")) & F.col("doc_id").eqNullSafe(F.col("_head")))
    lone = met.withColumn("_rank", rank).where("_rank = 1")
    return one.unionByName(lone.select(*docs.columns))
