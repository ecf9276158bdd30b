"""Substring near-duplicates by collinear chaining of shared k-mer seeds.

1. Seeds: every text's winnowed word 5-mers (the least hash of every ``WINDOW`` consecutive ones), so
   any run of ``K + WINDOW - 1`` common words holds a common seed; and winnowed runs of ``LONG`` words,
   whose holders have more than a stock phrase in common.
2. Each seed hash finds its first holder (least doc_id); every other holder matches that one only, so
   a passage in m documents makes m - 1 matches a seed, never m^2.  The first holder comes from a
   grouped minimum, combined on the map side; the join back can be split on hot seeds.
3. Per document, matches into the same other document are chained in order: the best chain ending in
   a match is found with a Fenwick tree of prefix maxima under linear gap costs, in O(n log n).
4. Chains are aligned on the words of both passages: anchors extend over equal words, gaps of unequal
   length by a small edit-distance table, ends outward through a few differences.
5. Aligned passages of ``MIN_PIECE`` words or more that are at least ``SIMILAR`` alike are united per
   document, whatever document holds their first copy; those of ``MIN_WORDS`` words are duplicates.

A passage that repeats itself within ``PERIOD`` words has no order to chain by.  There every run of
``MIN_WORDS`` words is a seed of its own, and a match is a passage as it stands.

Words are runs of bytes other than ASCII white space, compared with A-Z lowered.  Null and empty
texts have no words.  Rows with a null doc_id take no part.  Rows of one doc_id with one text are one
document; with different texts each text is a document, later than those whose id is not repeated.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import written
from .textscan import Scan, keyed, mix, slices, tidy

K = 5
WINDOW = 8
LONG, LONG_WINDOW = 16, 32
MAX_GAP = 40
GAP_COST = 0.05
MIN_CHAIN = 10
MIN_PIECE = 16
MIN_WORDS = 50
PERIOD = 16
SIMILAR = 0.8
MARGIN = 50
GRAIN = 64  # cut ranges begin and end at multiples of it, so that a document is asked for few different ones
CHAINED, SPREAD, WHOLE = range(3)  # kinds of seeds, in the two lowest bits of their hashes


def sliding(op: np.ufunc, x: np.ndarray, window: int) -> np.ndarray:
    """``op`` (a minimum or maximum) over every ``window`` consecutive values, by doubling."""
    size = 1
    while 2 * size <= window:
        x = op(x[:-size], x[size:])
        size *= 2
    return op(x[: len(x) - window + size], x[window - size :])


def winnow(s: Scan, k: int = K, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """(index of the first word in the scan, hash) of the selected k-mers of every document."""
    at, h = s.windows(s.word_hashes(lower=True), k)
    if not len(at):
        return at, h
    n = np.bincount(s.word_doc[at], minlength=s.n)
    n = n[n > 0]
    # documents laid out with window - 1 blanks around each, so that no window sees two documents
    blanks = window - 1
    shift = blanks * np.arange(1, len(n) + 1)
    place = np.arange(len(at)) + np.repeat(shift, n)
    laid = np.full(place[-1] + window, np.iinfo(np.uint64).max, np.uint64)
    laid[place] = h
    least = np.zeros(len(laid) + blanks, np.uint64)  # of the window that ends at a place, where that is a window of k-mers
    first = np.cumsum(n) - n + shift
    uses = np.zeros(len(laid) + 1, np.int8)
    uses[first] += 1
    uses[first + np.maximum(n - window, 0) + 1] -= 1
    begins = np.flatnonzero(np.cumsum(uses[:-1]))
    least[begins + blanks] = sliding(np.minimum, laid, window)[begins]
    # a k-mer is selected if some window that holds it has no lesser one
    chosen = sliding(np.maximum, least, window)[place] == h
    return at[chosen], h[chosen]


def fresh(s: Scan, at: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The selected k-mers that do not repeat one selected within the ``PERIOD`` words before."""
    doc, again = s.word_doc[at], np.zeros(len(at), bool)
    for lag in range(1, min(PERIOD + 1, len(at))):
        again[lag:] |= (h[lag:] == h[:-lag]) & (doc[lag:] == doc[:-lag]) & (at[lag:] - at[:-lag] <= PERIOD)
    return at[~again], h[~again]


def cycles(s: Scan) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first word, last word, hash): runs of ``MIN_WORDS`` words where the text repeats itself within ``PERIOD`` words.

    Equal runs not over ``MIN_WORDS`` words apart cover a stretch of text; first and last are their first words.
    """
    none = np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.uint64)
    words = s.word_hashes(lower=True)
    at, h = s.windows(words, K)
    if len(words) < MIN_WORDS or not len(at):
        return none
    doc = s.word_doc[at]
    near = np.zeros(len(at), bool)
    for lag in range(1, min(PERIOD + 1, len(at))):
        near[lag:] |= (h[lag:] == h[:-lag]) & (doc[lag:] == doc[:-lag])
    again = np.zeros(len(words) + 1, np.int64)
    again[at[near] + 1] = 1
    again = np.cumsum(again)
    n = len(words) - MIN_WORDS + 1
    there = np.flatnonzero((s.word_doc[:n] == s.word_doc[MIN_WORDS - 1 :]) & (again[MIN_WORDS - K + 1 :][:n] - again[:n] >= (MIN_WORDS - K) // 2))
    if not len(there):
        return none
    run = np.zeros(len(there), np.uint64)
    for j in range(MIN_WORDS):
        run = run * np.uint64(0x9E3779B97F4A7C15) + words[there + j]
    run = mix(run)
    order = np.argsort(keyed(run, s.word_doc[there]), kind="stable")
    there, run, doc = there[order], run[order], s.word_doc[there[order]]
    new = np.ones(len(there), bool)
    new[1:] = (run[1:] != run[:-1]) | (doc[1:] != doc[:-1]) | (np.diff(there) > MIN_WORDS)
    begins = np.flatnonzero(new)
    return there[begins], there[np.append(begins[1:], len(there)) - 1], run[begins]


def seeds(docs: DataFrame) -> DataFrame:
    """(seed, doc, pos, first) of documents (doc, text): seeds, their place, and whether it is the text's first such.

    ``pos`` is the word position, plus 2**32 times the words to the last run of a ``WHOLE`` seed's stretch.
    """

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in slices(b.column(1)):
                s = Scan(b.column(1).slice(lo, hi - lo))
                begin = np.searchsorted(s.word_doc, np.arange(s.n), "left")
                short, long, whole = fresh(s, *winnow(s)), fresh(s, *winnow(s, LONG, LONG_WINDOW)), cycles(s)
                at = np.concatenate([short[0], long[0], whole[0]])
                kind = np.repeat(np.arange(3, dtype=np.uint64), [len(short[0]), len(long[0]), len(whole[0])])
                h = mix(np.concatenate([short[1], long[1], whole[2]]) + kind) & ~np.uint64(3) | kind
                doc = s.word_doc[at]
                key = keyed(h, doc)
                order = np.argsort(key, kind="stable")
                new = np.ones(len(key), bool)
                new[1:] = key[order][1:] != key[order][:-1]
                first = np.zeros(len(key), bool)
                first[order[new]] = True
                pos = at - begin[doc]
                pos[len(pos) - len(whole[0]) :] += (whole[1] - whole[0]) << 32
                ids = b.column(0).slice(lo, hi - lo).to_numpy(zero_copy_only=False).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(ids[doc]), pa.array(pos), pa.array(first)], ["seed", "doc", "pos", "first"])

    return docs.select("doc", "text").mapInArrow(tidy(rows), "seed long, doc long, pos long, first boolean")


def matches(found: DataFrame) -> DataFrame:
    """(kind, doc, pos, far, other, other_pos): each seed of a document beside the first document that holds it."""
    only = F.col("first")
    heads = (
        found.groupBy(F.col("seed").alias("_seed"))
        .agg(F.min("doc").alias("other"), F.max("doc").alias("_last"), F.min_by(F.when(only, F.col("pos")), F.when(only, F.col("doc"))).alias("other_pos"))
        .where("other < _last")
        .drop("_last")
    )
    # written, so that both sides of the join are dealt by it alone and a hot seed's rows can be split
    heads = written(heads, "heads")
    met = found.join(heads, F.col("seed") == F.col("_seed")).where("doc > other")
    word = F.lit((1 << 32) - 1)
    return met.select(
        F.col("seed").bitwiseAND(F.lit(3)).cast("int").alias("kind"), "doc", F.col("pos").bitwiseAND(word).cast("int").alias("pos"),
        F.shiftright("pos", 32).cast("int").alias("far"), "other", F.col("other_pos").bitwiseAND(word).cast("int").alias("other_pos"),
    )


def anchors(matched: DataFrame) -> DataFrame:
    """(doc, pos, other, other_pos) of 5-mers: a match of a long run is that of its first and last."""
    steps = F.when(F.col("kind") == SPREAD, F.array(F.lit(0), F.lit(LONG - K))).otherwise(F.array(F.lit(0)))
    each = matched.where(F.col("kind") != WHOLE).withColumn("i", F.explode(steps))
    return each.select("doc", (F.col("pos") + F.col("i")).alias("pos"), "other", (F.col("other_pos") + F.col("i")).alias("other_pos"))


class PrefixMax:
    """Fenwick tree over positions 0..n-1: best (value, owner) among positions below a bound."""

    def __init__(self, n: int):
        self.value = [float("-inf")] * (n + 1)
        self.owner = [-1] * (n + 1)

    def put(self, at: int, value: float, owner: int) -> None:
        at += 1
        while at < len(self.value):
            if value > self.value[at]:
                self.value[at], self.owner[at] = value, owner
            at += at & -at

    def below(self, at: int) -> tuple[float, int]:
        best, owner = float("-inf"), -1
        while at > 0:
            if self.value[at] > best:
                best, owner = self.value[at], self.owner[at]
            at -= at & -at
        return best, owner


def chains(p: list[int], q: list[int], k: int = K, cost: float = GAP_COST, max_gap: int = MAX_GAP) -> list[list[int]]:
    """Chains (lists of match numbers, ascending in both positions) by falling score.

    ``p`` ascends.  A chain scores k a match less ``cost`` a word passed over in either text; matches
    go to the best chain that wants them, and a chain breaks where it passes over ``max_gap`` words.
    """
    rank = {v: i for i, v in enumerate(sorted(set(q)))}
    tree = PrefixMax(len(rank))
    score, before = [float(k)] * len(p), [-1] * len(p)
    i = 0
    while i < len(p):
        j = i
        while j < len(p) and p[j] == p[i]:  # equal p: none may precede another
            best, owner = tree.below(rank[q[j]])
            # the tree holds score + cost * (p + q), which makes its maximum that of the gap-costed score
            gained = best - cost * (p[j] + q[j]) + k
            if owner >= 0 and gained > k and p[j] - p[owner] <= max_gap and q[j] - q[owner] <= max_gap:
                score[j], before[j] = gained, owner
            j += 1
        for m in range(i, j):
            tree.put(rank[q[m]], score[m] + cost * (p[m] + q[m]), m)
        i = j
    used, out = [False] * len(p), []
    for end in sorted(range(len(p)), key=lambda x: (-score[x], x)):
        chain = []
        while end >= 0 and not used[end]:
            used[end] = True
            chain.append(end)
            end = before[end]
        if chain:
            out.append(chain[::-1])
    return out


def chained(matched: DataFrame, min_chain: int = MIN_CHAIN) -> DataFrame:
    """(doc, other, chain, anchors, other_anchors): chains that span ``min_chain`` words in both texts.

    A document's matches are gathered: a few a seed of its own at most, so the group is bounded by its text.
    """
    per_doc = matched.groupBy("doc").agg(F.array_sort(F.collect_set(F.struct("other", "pos", "other_pos"))).alias("m"))
    schema = "doc long, other long, anchors array<int>, other_anchors array<int>"

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc, other, left, right = [], [], [], []
            lists = b.column(1)
            flat = lists.flatten()
            o, p, q = (flat.field(i).to_numpy(zero_copy_only=False) for i in range(3))
            bounds = np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy())))
            for i, d in enumerate(b.column(0).to_pylist()):
                lo, hi = bounds[i], bounds[i + 1]
                cut = np.flatnonzero(np.diff(o[lo:hi])) + lo + 1
                for x, y in zip([lo, *cut.tolist()], [*cut.tolist(), hi], strict=True):
                    if y - x < 2 or p[y - 1] - p[x] + K < min_chain:
                        continue
                    ps, qs = p[x:y].tolist(), q[x:y].tolist()
                    for c in chains(ps, qs):
                        if ps[c[-1]] - ps[c[0]] + K >= min_chain and qs[c[-1]] - qs[c[0]] + K >= min_chain:
                            doc.append(d)
                            other.append(int(o[x]))
                            left.append([ps[j] for j in c])
                            right.append([qs[j] for j in c])
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(other, pa.int64()), pa.array(left, pa.list_(pa.int32())), pa.array(right, pa.list_(pa.int32()))], ["doc", "other", "anchors", "other_anchors"])

    return per_doc.mapInArrow(tidy(rows), schema)


def _outward(a: list[int], b: list[int], i: int, j: int, step: int) -> tuple[int, int]:
    """Words to add from (i, j) in direction ``step``, and how many of them are equal.

    Goes on through differences while at least 4 of 5 of what is added stay equal; ends on an equal word.
    """
    best = best_equal = n = equal = 0
    while 0 <= i < len(a) and 0 <= j < len(b) and n - equal <= 2 + best // 8:
        n += 1
        if a[i] == b[j]:
            equal += 1
            if 5 * equal >= 4 * n:
                best, best_equal = n, equal
        i += step
        j += step
    return best, best_equal


def _gap_equal(a: list[int], b: list[int]) -> int:
    """Longest common subsequence of two short gaps."""
    if len(a) == len(b):
        return sum(x == y for x, y in zip(a, b, strict=True))
    row = [0] * (len(b) + 1)
    for x in a:
        diagonal = 0
        for j, y in enumerate(b, 1):
            diagonal, row[j] = row[j], diagonal + 1 if x == y else max(row[j], row[j - 1])
    return row[-1]


def align(a: list[int], b: list[int], anchors: list[int], other: list[int], k: int = K) -> tuple[int, int, int, int, float]:
    """Bounds [a0, a1), [b0, b1) of the aligned passage and the share of its words that are equal."""
    equal, ia, ib = 0, anchors[0], other[0]
    a_from, b_from = ia, ib
    for p, q in zip(anchors, other, strict=True):
        if p > ia and q > ib:
            equal += _gap_equal(a[ia:p], b[ib:q])
        over = max(ia - p, ib - q, 0)
        equal += max(k - over, 0)
        ia, ib = max(ia, p + k), max(ib, q + k)
    n, e = _outward(a, b, a_from - 1, b_from - 1, -1)
    m, f = _outward(a, b, ia, ib, 1)
    a0, b0, a1, b1 = a_from - n, b_from - n, ia + m, ib + m
    return a0, a1, b0, b1, min(1.0, (equal + e + f) / max(a1 - a0, b1 - b0, 1))


def packed(docs: DataFrame) -> DataFrame:
    """``docs`` with ``text`` as Zstandard bytes, for shuffles that carry whole texts; null stays null."""
    names, at = list(docs.columns), docs.columns.index("text")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        for b in batches:
            small = pa.array([None if t is None else pack(t) for t in b.column(at).cast(pa.binary()).to_pylist()], pa.binary())
            yield pa.RecordBatch.from_arrays([small if i == at else c for i, c in enumerate(b.columns)], names)

    return docs.mapInArrow(tidy(rows), T.StructType([T.StructField(f.name, T.BinaryType()) if f.name == "text" else f for f in docs.schema]))


def unpacked(column: pa.Array) -> pa.Array:
    """The texts of a column of ``packed``."""
    unpack = zstandard.ZstdDecompressor().decompress
    return pa.array([None if t is None else unpack(t) for t in column.to_pylist()], pa.binary()).cast(pa.string())


def with_texts(small: DataFrame, schema: T.StructType) -> DataFrame:
    """The table that ``packed`` made ``small``."""
    names, at = list(small.columns), small.columns.index("text")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([unpacked(c) if i == at else c for i, c in enumerate(b.columns)], names)

    return small.mapInArrow(tidy(rows), schema)


def identified(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """(rows with a key ``doc``, keys of repeated ids): one key for each doc_id, or for each text of an id that has several.

    The key is the id itself but for those; then a written table has (doc, doc_id) of them, else there is none.
    """
    named = docs.where("doc_id is not null")
    texts = named.groupBy("doc_id").agg(F.min(F.xxhash64("text")).alias("lo"), F.max(F.xxhash64("text")).alias("hi"))
    several = written(texts.where("lo < hi").select(F.col("doc_id").alias("_several")), "several")
    plain = F.col("doc_id").cast("long")
    if several.isEmpty():
        return docs.withColumn("_doc", plain), None
    own = F.lit(1 << 62).bitwiseOR(F.xxhash64("doc_id", "text").bitwiseAND(F.lit((1 << 62) - 1)))
    keyed_rows = docs.join(several, F.col("doc_id") == F.col("_several"), "left").withColumn("_doc", F.when(F.col("_several").isNull(), plain).otherwise(own)).drop("_several")
    keyed_rows = written(keyed_rows, "identified")
    return keyed_rows, written(keyed_rows.where(F.col("_doc") != plain).select(F.col("_doc").alias("_key"), "doc_id").distinct(), "keys")


def passages(docs: DataFrame) -> DataFrame:
    """(doc, other, lo, hi, other_lo, other_hi, similarity) in words, of documents (doc, text): passages that are alike.

    Each has ``MIN_PIECE`` words or more; `other` is the first document (least key) that holds its seeds.
    """
    matched = written(matches(seeds(docs)), "matches")
    linked = written(chained(anchors(matched)), "chains")

    def down(c: Column) -> Column:
        return F.greatest(F.lit(0), F.floor((c - MARGIN) / GRAIN) * GRAIN).cast("int")

    def up(c: Column) -> Column:
        return (F.ceil((c + K + MARGIN) / GRAIN) * GRAIN).cast("int")

    sides = linked.select(
        "doc", "other", "anchors", "other_anchors",
        down(F.element_at("anchors", 1)).alias("lo"), up(F.element_at("anchors", -1)).alias("hi"),
        down(F.element_at("other_anchors", 1)).alias("other_lo"), up(F.element_at("other_anchors", -1)).alias("other_hi"),
    )
    asked = sides.select("doc", "lo", "hi").unionAll(sides.select("other", "other_lo", "other_hi"))
    asked = asked.groupBy("doc").agg(F.collect_set(F.struct("lo", "hi")).alias("ranges"))  # a text meets its ranges once
    texts = packed(docs.select(F.col("doc").alias("_doc"), "text"))
    pieces = _cut(asked.join(texts, F.col("doc") == F.col("_doc")).select("doc", "ranges", "text"))
    cut = written(pieces.groupBy("doc", "lo", "hi").agg(F.min("words").alias("words")), "pieces")  # one row even where a row repeats
    own = cut.select(F.col("doc").alias("_d"), F.col("lo").alias("_l"), F.col("hi").alias("_h"), F.col("words").alias("a"))
    far = cut.select(F.col("doc").alias("_od"), F.col("lo").alias("_ol"), F.col("hi").alias("_oh"), F.col("words").alias("b"))
    both = sides.join(own, (F.col("doc") == F.col("_d")) & (F.col("lo") == F.col("_l")) & (F.col("hi") == F.col("_h")))
    both = both.join(far, (F.col("other") == F.col("_od")) & (F.col("other_lo") == F.col("_ol")) & (F.col("other_hi") == F.col("_oh")))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for doc, other, p, q, lo, olo, a, b in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                a, b = np.frombuffer(a, np.uint64).tolist(), np.frombuffer(b, np.uint64).tolist()
                a0, a1, b0, b1, like = align(a, b, [x - lo for x in p], [x - olo for x in q])
                if like >= SIMILAR and a1 - a0 >= MIN_PIECE:
                    out.append((doc, other, a0 + lo, a1 + lo, b0 + olo, b1 + olo, like))
            cols = list(zip(*out, strict=True)) or [()] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names)

    names = ["doc", "other", "lo", "hi", "other_lo", "other_hi", "similarity"]
    kinds = [pa.int64(), pa.int64(), *[pa.int32()] * 4, pa.float64()]
    aligned = both.select("doc", "other", "anchors", "other_anchors", "lo", "other_lo", "a", "b").mapInArrow(tidy(rows), "doc long, other long, lo int, hi int, other_lo int, other_hi int, similarity double")
    stretch = (F.col("pos") + F.col("far") + MIN_WORDS).cast("int").alias("hi")
    whole = matched.where(F.col("kind") == WHOLE).select("doc", "other", F.col("pos").alias("lo"), stretch, F.col("other_pos").alias("other_lo"), (F.col("other_pos") + MIN_WORDS).cast("int").alias("other_hi"), F.lit(1.0).alias("similarity"))
    return aligned.unionByName(whole)


def _cut(rows_in: DataFrame) -> DataFrame:
    """The requested words of packed texts (doc, ranges, text) as their hashes, eight bytes a word."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, ids, asked = unpacked(b.column(2)), b.column(0).to_pylist(), b.column(1).to_pylist()
            for x, y in slices(texts):
                s = Scan(texts.slice(x, y - x))
                h = s.word_hashes(lower=True)
                begin = np.searchsorted(s.word_doc, np.arange(s.n + 1), "left").tolist()
                doc, lo, hi, words = [], [], [], []
                for i in range(x, y):
                    first, end = begin[i - x], begin[i - x + 1]
                    for r in asked[i]:
                        doc.append(ids[i])
                        lo.append(r["lo"])
                        hi.append(r["hi"])
                        words.append(h[min(first + r["lo"], end) : min(first + r["hi"], end)].tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(lo, pa.int32()), pa.array(hi, pa.int32()), pa.array(words, pa.binary())], ["doc", "lo", "hi", "words"])

    return rows_in.mapInArrow(tidy(rows), "doc long, lo int, hi int, words binary")


def united(found: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(doc, spans): a document's passages united where they touch, those of ``min_words`` or more.

    Spans are [from, to) in words, in order.  The fold walks one document's passages, which its text bounds.
    """
    ordered = found.groupBy("doc").agg(F.array_sort(F.collect_set(F.struct("lo", "hi"))).alias("p"))
    start = "cast(array() as array<struct<lo:int,hi:int>>)"
    grown = F.expr(
        f"aggregate(p, {start}, (acc, x) -> if(size(acc) > 0 and element_at(acc, -1).hi >= x.lo, "
        "concat(slice(acc, 1, size(acc) - 1), array(named_struct('lo', element_at(acc, -1).lo, 'hi', greatest(element_at(acc, -1).hi, x.hi)))), "
        "concat(acc, array(named_struct('lo', x.lo, 'hi', x.hi)))))"
    )
    return ordered.select("doc", F.filter(grown, lambda x: x["hi"] - x["lo"] >= min_words).alias("spans")).where(F.size("spans") > 0)


def duplicated_passages(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """One row per passage that repeats an earlier document's: doc_id, first_doc_id, word bounds, similarity.

    A passage counts if the united span that holds it has ``min_words`` words.
    """
    base, keys = identified(docs.select("doc_id", "text"))
    found = written(passages(base.where("_doc is not null").select(F.col("_doc").alias("doc"), "text")), "passages")
    spans = united(found, min_words).select(F.col("doc").alias("_doc"), "spans")
    rows = found.join(spans, F.col("doc") == F.col("_doc")).where(F.expr("exists(spans, s -> s.lo <= lo and s.hi >= hi)"))
    kind = docs.schema["doc_id"].dataType
    rows = rows.select(
        F.col("doc").alias("doc_id"), F.col("other").alias("first_doc_id"), F.col("lo").alias("from_word"), F.col("hi").alias("to_word"),
        F.col("other_lo").alias("first_from_word"), F.col("other_hi").alias("first_to_word"), "similarity",
    )
    for c in ("doc_id", "first_doc_id") if keys is not None else ():
        named = keys.select("_key", F.col("doc_id").cast("long").alias("_name"))
        rows = rows.join(named, F.col(c) == F.col("_key"), "left").withColumn(c, F.coalesce("_name", c)).drop("_key", "_name")
    return rows.withColumn("doc_id", F.col("doc_id").cast(kind)).withColumn("first_doc_id", F.col("first_doc_id").cast(kind))


def without_passages(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """``docs`` with repeated passages cut from their texts, all columns and rows kept.

    The first document that holds a passage keeps it.  What is left is joined by line feeds; ``n_chars``,
    where there is such a column, follows the new text.
    """
    base, _ = identified(docs)
    found = written(passages(base.where("_doc is not null").select(F.col("_doc").alias("doc"), "text")), "passages")
    spans = united(found, min_words).select(F.col("doc").alias("_of"), F.col("spans").alias("_spans"))
    joined = packed(base).join(spans, F.col("_doc") == F.col("_of"), "left")
    names, at = list(docs.columns), docs.columns.index("text")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = unpacked(b.column(at))
            lists = b.column(b.num_columns - 1).to_pylist()
            if any(lists):
                new = [cut_text(t, x) if x and t is not None else t for t, x in zip(texts.to_pylist(), lists, strict=True)]
                texts = pa.array(new, texts.type)
            columns = [texts if i == at else c for i, c in enumerate(b.columns[:-1])]
            yield pa.RecordBatch.from_arrays(columns, names)

    out = joined.select(*docs.columns, "_spans").mapInArrow(tidy(rows), docs.schema)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)).select(*docs.columns)
    return out


def cut_text(text: str, spans: list[dict]) -> str:
    """``text`` less the words of the spans and the white space after them."""
    data = text.encode()
    s = Scan(pa.array([text], pa.string()))
    kept, upto = [], 0
    for x in spans:
        if x["lo"] >= len(s.starts):
            continue
        kept.append(data[upto : s.starts[x["lo"]]])
        upto = int(s.starts[x["hi"]]) if x["hi"] < len(s.starts) else len(data)
    kept.append(data[upto:])
    parts = [k.decode().strip(" \t\n\r\x0b\x0c") for k in kept]
    return "\n".join(p for p in parts if p)
