"""Mixing sources to target weights by capped water-filling, in DataFrame operations only.

Each source asks for its share of the mix by weight but may give at most ``max_epochs`` times its
size; what it cannot give is reshared among the others by weight, until none is above its cap.  That
fixed point is a water level: with sources ordered by size over weight, one is capped exactly if its
cap is at most its share of what the sources from it onwards must give.

A source is then taken in whole epochs plus a seeded part of one more.  The part is a prefix of the
source in hash order, found from three levels of sums over hash buckets rather than a sort: all buckets
below the cut, and of the cut bucket's sub-buckets and documents those up to the target.  Rows that
agree in id and size have one hash; the last step deals them by their place in the table, so they need
not all go in or stay out.  Only sums of a bounded number of buckets a source are shuffled, however many
rows a source has.

Sizes are counts of words (runs of characters other than space and 0x09-0x0D); a null text has none.
Sources are ordered by code point with null last and weigh ``WEIGHTS`` in turn.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .common import written

WEIGHTS = (5, 2, 1)
SHARE = (3, 2)  # the mix has 3/2 of all words
MAX_EPOCHS = 2
SEED = "mix-1"
BUCKET_DIGITS = 3  # hex digits of a level: 4096 buckets
FEW_SOURCES = 50_000  # rows of the plan that are broadcast; more are joined by a shuffle
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: tuple[int, int] = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """(source, source_size, target) from (source, source_size), one row a source.

    The windows run over one row a source, not over documents.
    """
    by_name = W.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int"))
    w = sizes.withColumn("_w", weight.cast("long")).withColumn("_need", F.lit(share[0]) * F.sum("source_size").over(W.partitionBy()))
    onward = W.orderBy(F.col("source_size") / F.col("_w"), F.col("source").asc_nulls_last()).rowsBetween(W.currentRow, W.unboundedFollowing)
    before = W.orderBy(F.col("source_size") / F.col("_w"), F.col("source").asc_nulls_last()).rowsBetween(W.unboundedPreceding, -1)
    # whole numbers up to here: _left is what this source and those after it must give, times share[1]
    w = w.withColumn("_rest", F.sum("_w").over(onward)).withColumn(
        "_left", F.col("_need") - share[1] * max_epochs * F.coalesce(F.sum("source_size").over(before), F.lit(0))
    )
    capped = (max_epochs * share[1] * F.col("source_size")).cast("double") * F.col("_rest") <= F.col("_w").cast("double") * F.col("_left")
    w = w.withColumn("_capped", capped)
    # the first source that is not capped, and all after it, share what is left there
    least = F.min(F.when(~F.col("_capped"), F.struct((-F.col("_rest")).alias("k"), F.col("_rest").alias("rest"), F.col("_left").alias("left")))).over(W.partitionBy())
    w = w.withColumn("_level", least)
    shared = F.col("_w").cast("double") * F.col("_level.left") / (F.lit(share[1]).cast("double") * F.col("_level.rest"))
    cap = (max_epochs * F.col("source_size")).cast("double")
    return w.select("source", "source_size", F.when(F.col("_capped") | F.col("_level").isNull(), cap).otherwise(F.least(cap, shared)).alias("target"))


def mark() -> Column:
    """Hex digits that order a source's documents at random, the same in every run."""
    return F.md5(F.concat(F.lit(SEED + ":"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), word_count().cast("string")))


def place() -> Column:
    """Where a row stands in its table: tells rows of one mark apart."""
    return F.monotonically_increasing_id()


def order_key() -> Column:
    """What a source's rows are ordered by, from ``mark`` and ``place``: three levels of buckets, the last by both."""
    apart = F.substring(F.md5(F.col("place").cast("string")), 1, BUCKET_DIGITS)
    return F.concat(F.substring("mark", 1, 3 * BUCKET_DIGITS), apart)


def plan(rows: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: tuple[int, int] = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """(source, source_size, target, epochs, below), one row a source, from rows (source, size, mark, place).

    Every row of a source is taken ``epochs`` times, and once more if its order key sorts before
    ``below``.
    """
    coarse, fine = F.substring("mark", 1, BUCKET_DIGITS), F.substring("mark", 1, 2 * BUCKET_DIGITS)
    buckets = rows.groupBy("source", coarse.alias("bucket")).agg(F.sum("size").alias("n"))
    aims = targets(buckets.groupBy("source").agg(F.sum("n").alias("source_size")), weights, share, max_epochs)
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    aims = aims.withColumn("epochs", epochs).withColumn("part", F.col("target") - F.col("epochs") * F.col("source_size"))
    first = _cut(buckets, aims.select(F.col("source").alias("of"), F.col("part").alias("want")))
    cuts = first.select(F.col("of").alias("cut_of"), F.col("cut").alias("cut_bucket"), F.col("left").alias("cut_left"))
    inside = rows.join(cuts, F.col("source").eqNullSafe(F.col("cut_of")) & (coarse == F.col("cut_bucket")))
    second = _cut(inside.groupBy("source", fine.alias("bucket")).agg(F.sum("size").alias("n")), cuts.select(F.col("cut_of").alias("of"), F.col("cut_left").alias("want")))
    fines = second.select(F.col("of").alias("fine_of"), F.col("cut").alias("fine_bucket"), F.col("left").alias("fine_left"))
    last = rows.join(fines, F.col("source").eqNullSafe(F.col("fine_of")) & (fine == F.col("fine_bucket"))).groupBy("source", order_key().alias("bucket")).agg(F.sum("size").alias("n"))
    third = _cut(last, fines.select(F.col("fine_of").alias("of"), F.col("fine_left").alias("want")))
    # the last bucket goes in whole if most of it is wanted; 'g' sorts after every hex digit
    ends = third.select("of", F.when(2 * F.col("left") >= F.col("cut_n"), F.concat("cut", F.lit("g"))).otherwise(F.col("cut")).alias("end"))
    return aims.join(ends, F.col("source").eqNullSafe(F.col("of")), "left").select(
        "source", "source_size", "target", "epochs", F.when(F.col("part") <= 0, "").otherwise(F.coalesce("end", F.lit("g"))).alias("below")
    )


def _cut(buckets: DataFrame, wanted: DataFrame) -> DataFrame:
    """(of, cut, left, cut_n): the bucket in which a source's wanted words end, and how many of them it must give."""
    upto = buckets.withColumn("upto", F.sum("n").over(W.partitionBy("source").orderBy("bucket")))
    over = upto.join(wanted, F.col("source").eqNullSafe(F.col("of"))).where("upto > want")
    end = F.min(F.struct("bucket", (F.col("want") - F.col("upto") + F.col("n")).alias("left"), "n"))
    return over.groupBy("of").agg(end.alias("e")).select("of", F.col("e.bucket").alias("cut"), F.col("e.left").alias("left"), F.col("e.n").alias("cut_n"))


def _planned(docs: DataFrame, weights: tuple[int, ...], share: tuple[int, int], max_epochs: int) -> tuple[DataFrame, DataFrame]:
    """The sized rows and the plan, both written; the plan is broadcast if it has few sources."""
    rows = written(docs.select("doc_id", "source", word_count().alias("size"), mark().alias("mark"), place().alias("place")), "sizes")
    by_source = written(plan(rows, weights, share, max_epochs), "mix").withColumnRenamed("source", "_source")
    return rows, F.broadcast(by_source) if by_source.count() <= FEW_SOURCES else by_source


def _repeats() -> Column:
    return (F.col("epochs") + (order_key() < F.col("below")).cast("long")).cast("long")


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: tuple[int, int] = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """doc_id, size, source_size, target, taken, repeats for every row of ``docs``.

    ``repeats`` is how often the mix takes the row, ``taken`` its words, repeats counted.  A row
    without words is repeated like the others of its source and takes none.
    """
    rows, by_source = _planned(docs, weights, share, max_epochs)
    joined = rows.join(by_source, F.col("source").eqNullSafe(F.col("_source"))).withColumn("repeats", _repeats())
    return joined.select("doc_id", "size", "source_size", "target", (F.col("repeats") * F.col("size")).alias("taken"), "repeats")


def mixed_rows(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: tuple[int, int] = SHARE, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """The mix itself: rows of ``docs`` with all their columns, each as often as the mix takes it."""
    _, by_source = _planned(docs, weights, share, max_epochs)
    mine = by_source.select(F.col("_source").alias("_of"), F.col("epochs").alias("_epochs"), F.col("below").alias("_below"))
    own = docs.select("*", mark().alias("_mark"), place().alias("_place"))
    key = F.concat(F.substring("_mark", 1, 3 * BUCKET_DIGITS), F.substring(F.md5(F.col("_place").cast("string")), 1, BUCKET_DIGITS))
    times = F.col("_epochs") + (key < F.col("_below")).cast("long")
    joined = own.join(mine, F.col("source").eqNullSafe(F.col("_of")))
    return joined.withColumn("_copy", F.explode(F.array_repeat(F.lit(0), times.cast("int")))).select(*docs.columns)
