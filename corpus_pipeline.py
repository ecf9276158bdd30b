"""The corpus pipeline: a table of documents through five operators, each stage on all that is left.

Every stage is ``f(spark, docs, sf_dir) -> DataFrame``; its result is written as Parquet and read again
as the next stage's documents.  All but the last return the columns of documents, extra ones included.

1. quality classifier: documents scored below the threshold go
2. SimHash near-duplicates of five-word shingles, by bands beyond the balls' radius, all verified at a
   similarity of 0.8: one document of each group stays
3. substring deduplication: passages that repeat an earlier document's are cut from texts
4. mixing: rows as often as their source's target asks
5. byte-level BPE: token ids beside the columns of documents
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from roilens.llm import alike, bpe, mixing, quality_pu, substring
from roilens.llm.common import table, written
from roilens.llm.registry import RANK_FILE


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the positive-unlabelled classifier scores at its threshold or over."""
    return quality_pu.keep_good(docs, quality_pu.fit(spark, docs, table(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group linked by five-word shingle similarity of 0.8 or more."""
    return alike.keep_one(docs)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, without passages that an earlier document has."""
    return substring.without_passages(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows repeated as the mix asks."""
    return mixing.mixed_rows(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows with their token ids."""
    return bpe.encode_column(docs, public_tokenizers.path(RANK_FILE), public_tokenizers.PATTERN)


STAGES = [
    ("quality classifier", quality),
    ("near duplicates", near_duplicates),
    ("substring dedup", repeated_passages),
    ("source mix", mix),
    ("byte-level BPE", encode),
]

#: Trained models and chaining have no SQL; the stages are tested against brute-force versions instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
