"""Document fingerprints by randomised edit embedding.

All texts take walks that share one source of randomness: at step j the walk writes the character it
stands on and then stays or moves on, by a random bit that depends on j and the character only.  Two
texts at small edit distance soon walk in step again after each edit, so that edit distance turns into
Hamming distance between what they wrote.  Steps are bit-sampled: each of ``SLOTS`` slots keeps the
character written at one sampled step and hashes it to four bits.  The sampled step of a slot is the
record holder of a random order among the steps taken, so texts of like length sample the same steps
and long walks are covered from end to end.

Walks of many texts advance together in numpy, so the Python cost is per step, not per character.
A walk over n characters takes 2n + 16 steps; at the end of its text it writes blanks.  Null and empty
texts write only blanks, equal texts have equal fingerprints.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .alike import blocks
from .common import written
from .components import components
from .textscan import slices

SLOTS = 128
BANDS, BAND_SLOTS = 32, 6
SEED = 2024
WALK_CHARS = 8 << 20

_rng = np.random.default_rng(SEED)
_PERIOD = 4096
_MOVES = _rng.integers(0, 2, (_PERIOD, 256), dtype=np.int64)
_MOVES[:, 0] = 0  # a blank is never left
_NIBBLE = _rng.integers(0, 16, (SLOTS, 256), dtype=np.uint8)
_NIBBLE[:, 0] = 0
FIRST_STEPS = 16  # every slot begins with a sample of one of these
_records: list[np.ndarray] = [np.sort(np.arange(SLOTS) % FIRST_STEPS), np.argsort(np.arange(SLOTS) % FIRST_STEPS, kind="stable"), np.zeros(1, np.int64)]
_slot_best = np.full(SLOTS, 1.0)


def _sampled_steps(upto: int) -> tuple[np.ndarray, np.ndarray]:
    """Steps below ``upto`` at which a slot takes a new sample, and those slots; a fixed schedule."""
    done = int(_records[2][0])
    while done < upto:
        block = np.random.default_rng((SEED, done))
        slots, order = block.integers(0, SLOTS, 1 << 16), block.random(1 << 16)
        at = []
        for j in np.flatnonzero(order < _slot_best[slots]).tolist():
            if order[j] < _slot_best[slots[j]] and j + done >= FIRST_STEPS:
                _slot_best[slots[j]] = order[j]
                at.append(j)
        _records[0] = np.concatenate([_records[0], np.array(at, np.int64) + done])
        _records[1] = np.concatenate([_records[1], slots[at]])
        done += 1 << 16
    _records[2][0] = done
    n = int(np.searchsorted(_records[0], upto))
    return _records[0][:n], _records[1][:n]


def _code(points: np.ndarray) -> np.ndarray:
    """Code points to 1..255; 0 is the blank."""
    return (points.astype(np.uint32) * np.uint32(2654435761) >> np.uint32(8)) % np.uint32(255) + np.uint32(1)


def embed(texts: list[str]) -> np.ndarray:
    """texts x ``SLOTS`` half-bytes."""
    n = np.array([len(t) for t in texts], np.int64)
    out = np.zeros((len(texts), SLOTS), np.uint8)
    order = np.argsort(-n, kind="stable")
    todo = 0
    while todo < len(order):  # texts of like length walk together, some millions of characters at a time
        size = np.cumsum(n[order[todo:]] + 1)
        upto = todo + max(1, int(np.searchsorted(size, WALK_CHARS)))
        group = order[todo:upto]
        out[group] = _walk([texts[i] for i in group.tolist()], n[group])
        todo = upto
    return out


def _walk(texts: list[str], n: np.ndarray) -> np.ndarray:
    flat = np.frombuffer("\0".join([*texts, ""]).encode("utf-32-le", "surrogatepass"), np.uint32)
    ends = np.cumsum(n + 1) - 1
    codes = _code(flat).astype(np.uint8)
    codes[ends] = 0
    at = ends - n
    steps = 2 * n + 16  # falls along the group
    wrote = np.zeros((SLOTS, len(texts)), np.uint8)
    when, slot = _sampled_steps(int(steps[0]))
    active = np.searchsorted(-steps, -np.arange(int(steps[0])), "left")  # walks with more than j steps
    k, next_at = 0, int(when[0]) if len(when) else -1
    active_list = active.tolist()
    here, moves = at, _MOVES
    last = len(texts)
    for j, a in enumerate(active_list):
        if a != last:
            here, last = at[:a], a
        c = codes[here]
        while j == next_at:
            wrote[slot[k], :a] = c
            k += 1
            next_at = int(when[k]) if k < len(when) else -1
        here += moves[j & 4095][c]
    return _NIBBLE[np.arange(SLOTS)[:, None], wrote].T


def to_hex(marks: np.ndarray) -> list[str]:
    """Fingerprints as hex strings, a digit a slot."""
    packed = (marks[:, 0::2] << 4 | marks[:, 1::2]).astype(np.uint8)
    return [row.tobytes().hex() for row in packed]


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Share of equal slots, row by row: 1 less the sampled Hamming distance."""
    return (a == b).mean(1) if len(a) else np.zeros(0)


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint) of every row, in one pass."""
    base = docs.select("doc_id", "text")
    schema = T.StructType([base.schema["doc_id"], T.StructField("fingerprint", T.StringType())])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in slices(b.column(1)):
                texts = [t or "" for t in b.column(1).slice(lo, hi - lo).to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array(to_hex(embed(texts)), pa.string())], schema.names)

    return base.mapInArrow(rows, schema)


def edited_text(own: str, following: str) -> str:
    """The last half of ``own`` (rounded down) gives way to as much of the beginning of ``following``."""
    half = len(own) // 2
    return own[: len(own) - half] + following[:half]


def _bands(fps: DataFrame) -> DataFrame:
    """(fingerprint, band, key): ``BANDS`` samples of ``BAND_SLOTS`` digits each of a fingerprint."""
    rng = np.random.default_rng(SEED + 1)
    picks = [sorted(rng.choice(SLOTS, BAND_SLOTS, replace=False).tolist()) for _ in range(BANDS)]
    keys = F.array(*(F.concat(*(F.substring("fingerprint", s + 1, 1) for s in p)) for p in picks))
    return fps.select("fingerprint", F.posexplode(keys).alias("band", "key"))


def likeness_column(a: str, b: str):
    """Share of equal hex digits of two fingerprint columns, in Spark expressions."""
    return F.expr(f"aggregate(sequence(1, {SLOTS}), 0, (n, i) -> n + if(substring({a}, i, 1) = substring({b}, i, 1), 1, 0))") / F.lit(float(SLOTS))


def near_links(marked: DataFrame, at_least: float = 0.8) -> DataFrame:
    """(a, b, likeness): verified links that connect all alike fingerprints of ``marked`` that share a band.

    Equal fingerprints are folded first.  In every bucket members meet the least one, which joins most
    groups in m - 1 candidates.  Mates in buckets that then still hold several components all meet, in
    blocks of bounded size; only links become rows, one for two components of a block.  So two alike
    fingerprints that share a bucket are never left unconnected.
    """
    fps = marked.select("fingerprint").distinct()
    banded = written(_bands(fps), "bands")

    def alike(pairs: DataFrame) -> DataFrame:
        return written(pairs.distinct().withColumn("likeness", likeness_column("a", "b")).where(F.col("likeness") >= at_least), "near-links")

    least = banded.groupBy("band", "key").agg(F.min("fingerprint").alias("a"), F.max("fingerprint").alias("z")).where("a < z").drop("z")
    first = alike(banded.join(least, ["band", "key"]).where("fingerprint > a").select("a", F.col("fingerprint").alias("b")))
    roots = components(first.select("a", "b"))
    held = banded.join(roots, F.col("fingerprint") == F.col("node"), "left").select("band", "key", "fingerprint", F.coalesce("root", "fingerprint").alias("comp"))
    held = written(held, "bands")
    keyed = held.select(F.concat_ws(":", "band", "key").alias("key"), F.col("fingerprint").alias("node"), F.lit(SLOTS).cast("long").alias("size"), "comp")
    of = held.select(F.col("fingerprint").alias("_f"), "comp").distinct()
    met = written(blocks(keyed), "blocks").join(of, F.col("node") == F.col("_f")).select("block", "node", "comp")

    def links(group: pa.Table) -> pa.Table:
        return block_links(group.column("node").to_pylist(), group.column("comp").to_pylist(), at_least)

    second = written(met.groupBy("block").applyInArrow(links, "a string, b string, likeness double"), "near-links")
    return first.unionAll(second).distinct()


def block_links(marks: list[str], comps: list[str], at_least: float) -> pa.Table:
    """(a, b, likeness): for two components that have alike members among these fingerprints, one such pair."""
    _, comp = np.unique(np.array(comps), return_inverse=True)
    digits = np.frombuffer("".join(marks).encode(), np.uint8).reshape(len(marks), SLOTS)
    found: dict[tuple[int, int], tuple[str, str, float]] = {}
    for i in range(1, len(marks)):
        others = np.flatnonzero(comp[:i] != comp[i])
        like = (digits[others] == digits[i]).sum(1) / SLOTS
        for j in others[like >= at_least].tolist():
            pair = (min(comp[i], comp[j]), max(comp[i], comp[j]))
            if pair not in found:
                found[pair] = (min(marks[i], marks[j]), max(marks[i], marks[j]), float((digits[i] == digits[j]).sum() / SLOTS))
    cols = list(zip(*found.values(), strict=True)) or [()] * 3
    return pa.table([pa.array(c, k) for c, k in zip(cols, (pa.string(), pa.string(), pa.float64()), strict=True)], ["a", "b", "likeness"])


def near_groups(docs: DataFrame, at_least: float = 0.8) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row: components of texts whose fingerprints are alike.

    component_id is the least doc_id reachable, null where no text of the component has one.  Null texts
    are empty ones; empty texts are like each other.
    """
    marked = written(fingerprints(docs), "marked")
    roots = components(near_links(marked, at_least).select("a", "b"))
    rooted = marked.join(roots, F.col("fingerprint") == F.col("node"), "left").select("doc_id", "fingerprint", F.coalesce("root", "fingerprint").alias("root"))
    ids = rooted.groupBy(F.col("root").alias("of")).agg(F.min("doc_id").alias("component_id"))
    return rooted.join(ids, F.col("root") == F.col("of")).select("doc_id", "fingerprint", "component_id")


def _cut_points(docs: DataFrame, parts: int) -> list[int]:
    """At most ``parts - 1`` ids that part the documents about evenly."""
    if parts < 2:
        return []
    at = docs.agg(F.percentile_approx("doc_id", F.array(*(F.lit(i / parts) for i in range(1, parts))), F.lit(10000)).alias("c")).first().c
    return sorted(set(at or []))


def _own_partition(spark: SparkSession, parts: list[int]) -> Column:
    """A key by whose hash every value of ``part`` has a shuffle partition of its own, if there are as many as values."""
    n = max(len(parts), 1)
    number = F.col("id").cast("int")
    # of some times as many numbers, the least that falls into each partition
    least = spark.range(40 * n + 100).groupBy(F.pmod(F.hash(number), F.lit(n)).alias("p")).agg(F.min(number).alias("key")).collect()
    keys = {r.p: r.key for r in least}
    of = [keys.get(i, i) for i in range(n)]
    rank = {p: i for i, p in enumerate(parts)}
    return F.element_at(F.array(*(F.lit(of[rank[p]]) if p in rank else F.lit(0) for p in range(max(parts, default=0) + 1))), F.col("part") + 1)


def edit_study(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness.

    The next document is found without one global sort: ids are dealt into ranges in descending
    order, each range also gets a copy of the first document of the range after it (one a range), and
    the ranges are read as sorted streams.  Rows with equal ids follow each other by text; null ids
    come last.
    """
    spark = docs.sparkSession
    parts = parts or max(2, int(spark.conf.get("spark.sql.shuffle.partitions")) * 2)
    base = docs.select("doc_id", "text")
    cuts = _cut_points(base, parts)
    # range 0 holds the largest ids; nulls have a range of their own at the end
    over = F.size(F.filter(F.array(*(F.lit(c) for c in cuts)), lambda c: F.col("doc_id") > c)) if cuts else F.lit(0)
    number = F.lit(len(cuts)) - over
    number = F.when(F.col("doc_id").isNull(), len(cuts) + 1).otherwise(number)
    ranged = base.withColumn("part", number)
    # the first document of each range: greatest id, then least text; as many rows as ranges
    tops = ranged.groupBy("part").agg(F.max("doc_id").alias("top")).collect()
    order = sorted((r.part, r.top) for r in tops)
    copies = [(order[i - 1][0], top, i == 0) for i, (_, top) in enumerate(order)]
    if not copies:
        copies = [(0, None, True)]
    heads = spark.createDataFrame([(p, t) for p, t, _ in copies], "part int, top long")
    first = base.join(F.broadcast(heads), F.col("doc_id").eqNullSafe(F.col("top"))).groupBy("part", "doc_id").agg(F.min(F.coalesce("text", F.lit(""))).alias("text"))
    rows_in = ranged.select("part", "doc_id", "text", F.lit(0).alias("copy")).unionByName(first.select("part", "doc_id", "text", F.lit(1).alias("copy")))
    dealt = rows_in.repartition(max(len(order), 1), _own_partition(spark, [p for p, _ in order])).sortWithinPartitions("part", "copy", F.col("doc_id").desc_nulls_last(), F.coalesce("text", F.lit("")))
    schema = T.StructType(
        [base.schema["doc_id"], T.StructField("n_chars", T.LongType())]
        + [T.StructField(c, T.StringType()) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")]
        + [T.StructField(c, T.DoubleType()) for c in ("near_edited", "near_next")]
    )

    def study(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: list[tuple] = []  # rows whose next is not read yet come first in the next turn
        size = 0

        def flush(rows: list[tuple]) -> pa.RecordBatch:
            own = [r[2] for r in rows]
            edited = [edited_text(a, b) if rows[i][3] == 0 else "" for i, (a, b) in enumerate(zip(own, own[1:], strict=False))]
            marks = embed(own + edited)
            m, e = marks[: len(own)], marks[len(own) :]
            use = [i for i in range(len(rows) - 1) if rows[i][3] == 0]
            ids, u = [rows[i][1] for i in use], np.array(use, np.int64)
            return pa.RecordBatch.from_arrays(
                [
                    pa.array(ids, pa.int64()),
                    pa.array([len(own[i]) for i in use], pa.int64()),
                    pa.array([hashlib.sha256(edited[i].encode()).hexdigest() for i in use], pa.string()),
                    pa.array(to_hex(m[u]), pa.string()),
                    pa.array(to_hex(e[u]), pa.string()),
                    pa.array(likeness(m[u], e[u])),
                    pa.array(likeness(m[u], m[u + 1])),
                ],
                schema.names,
            )

        for b in batches:
            for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
                part, doc_id, text, copy = row
                waiting.append((part, doc_id, text or "", copy))
                size += len(waiting[-1][2])
                if size > WALK_CHARS and len(waiting) > 2:
                    yield flush(waiting)
                    waiting, size = waiting[-1:], len(waiting[-1][2])
        if len(waiting) > 1:
            yield flush(waiting)

    return dealt.mapInArrow(study, schema)
