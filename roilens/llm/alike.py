"""Near-duplicates at a Jaccard similarity of five-word shingles of at least ``SIMILAR``, SimHash first.

1. Texts with one shingle set are folded to one node; sets are compared once, however many copies.
2. Ball hashing (``simhash.links``) over SimHash fingerprints of the shingle sets finds nodes within its
   radius.  Sets of similarity 0.8 differ in 9.7 of 64 bits on average, which no ball of a bearable
   size reaches, so this links close copies only.
3. For the others a set has ``BANDS`` bucket keys of ``ROWS`` least hashes each; two sets of similarity
   0.8 share none with a chance of 3 in a million.  In every bucket all nodes are compared with the
   least one, which joins a group of like texts in as many comparisons as it has members.
4. In buckets that still hold several components all mates are compared, in blocks of bounded size, so
   no link between bucket mates is missed.  No pair of mates becomes a row, only links do.

Every link is verified on whole shingle sets.  Words are runs of bytes other than ASCII white space,
compared with A-Z lowered.  A text of fewer than five words is one shingle; null and empty texts have
none and are like each other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import written
from .components import components
from .substring import packed, unpacked
from .textscan import Scan, mix, slices, tidy

SHINGLE = 5
SIMILAR = 0.8
BANDS, ROWS = 32, 5
CHUNK = 256  # pairs whose shingle sets a worker holds at a time
BLOCK_NODES, BLOCK_SHINGLES = 400, 150_000  # of a bucket's parts, on average; two make a block
CELLS = 1 << 22  # of a block's incidence matrix that are laid out at a time

_rng = np.random.default_rng(5)
_XOR = _rng.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)
_ODD = _rng.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)


def shingle_sets(s: Scan, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of every document's distinct shingles, ascending in both."""
    words = s.word_hashes(lower=True)
    at, h = s.windows(words, k)
    n = s.words_per_doc()
    begin = np.concatenate(([0], np.cumsum(n)))[:-1]
    short = np.flatnonzero((n > 0) & (n < k))
    whole = np.zeros(len(short), np.uint64)
    for j in range(k - 1):
        has = n[short] > j
        whole[has] = mix(whole[has] + words[begin[short[has]] + j] + np.uint64(j + 1))
    doc, h = np.concatenate([s.word_doc[at], short]), np.concatenate([h, whole])
    order = np.lexsort([h, doc])
    doc, h = doc[order], h[order]
    new = np.ones(len(h), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])
    return doc[new], h[new]


def node_ids(doc: np.ndarray, h: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray]:
    """(id of the shingle set, its size) of every document; equal sets have equal ids."""
    size = np.bincount(doc, minlength=n_docs).astype(np.int64)
    ids = np.zeros(n_docs, np.uint64)
    used = np.flatnonzero(size)
    if len(used):
        ids[used] = np.add.reduceat(mix(h ^ np.uint64(0x2545F4914F6CDD1D)), np.concatenate(([0], np.cumsum(size[used])[:-1])))
    return mix(ids + size.astype(np.uint64)), size


def fingerprints(h: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The 64-bit SimHash of every document's shingle set; zero for an empty one."""
    ends = np.cumsum(size)
    ones = np.zeros((len(size), 64), np.int64)
    for lo in range(0, len(h), 1 << 17):
        bits = np.unpackbits(h[lo : lo + (1 << 17)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        first, last = np.searchsorted(ends, [lo, lo + len(bits) - 1], "right")
        has = np.flatnonzero(size[first : last + 1]) + first
        ones[has] += np.add.reduceat(bits, np.maximum(ends[has] - size[has] - lo, 0), axis=0, dtype=np.int64)
    return np.packbits(2 * ones > size[:, None], axis=1, bitorder="little").view(np.uint64).ravel()


def band_keys(h: np.ndarray, size: np.ndarray) -> np.ndarray:
    """documents with shingles x ``BANDS``: the bucket keys; ``size`` has no zeros."""
    begin = np.concatenate(([0], np.cumsum(size)[:-1]))
    keys = np.empty((len(size), BANDS), np.uint64)
    for b in range(BANDS):
        key = np.full(len(size), b + 1, np.uint64)
        for i in range(b * ROWS, (b + 1) * ROWS):
            key = mix(key + np.minimum.reduceat((h ^ _XOR[i]) * _ODD[i], begin))
        keys[:, b] = key
    return keys


def _marked(docs: DataFrame) -> DataFrame:
    """(doc_id, node, size, fp, bands) of every row."""
    base = docs.select("doc_id", "text")
    kind = base.schema["doc_id"].dataType.simpleString()

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in slices(b.column(1)):
                s = Scan(b.column(1).slice(lo, hi - lo))
                doc, h = shingle_sets(s)
                ids, size = node_ids(doc, h, s.n)
                used = size > 0
                keys = band_keys(h, size[used]).ravel() if used.any() else np.empty(0, np.uint64)
                ends = np.concatenate(([0], np.cumsum(np.where(used, BANDS, 0)))).astype(np.int32)
                bands = pa.ListArray.from_arrays(pa.array(ends), pa.array(keys.view(np.int64)))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array(ids.view(np.int64)), pa.array(size), pa.array(fingerprints(h, size).view(np.int64)), bands], ["doc_id", "node", "size", "fp", "bands"])

    return base.mapInArrow(tidy(rows), f"doc_id {kind}, node long, size long, fp long, bands array<long>")


def text_nodes(texts: pa.Array) -> np.ndarray:
    """The node of every text, as signed longs."""
    out = [np.empty(0, np.uint64)]
    for lo, hi in slices(texts):
        s = Scan(texts.slice(lo, hi - lo))
        out.append(node_ids(*shingle_sets(s), s.n)[0])
    return np.concatenate(out).view(np.int64)


def _sets(docs: DataFrame, marked: DataFrame, wanted: DataFrame) -> DataFrame:
    """(node, shingles): the sorted shingle hashes of the wanted nodes, eight bytes each.

    Only texts of wanted nodes' first rows travel; nodes without an id take any of their rows.
    """

    def with_node(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = unpacked(b.column(0))
            for lo, hi in slices(texts):
                s = Scan(texts.slice(lo, hi - lo))
                doc, h = shingle_sets(s)
                ids, size = node_ids(doc, h, s.n)
                ends = np.concatenate(([0], np.cumsum(size)))
                sets = [h[ends[i] : ends[i + 1]].tobytes() for i in range(s.n)]
                yield pa.RecordBatch.from_arrays([pa.array(ids.view(np.int64)), pa.array(sets, pa.binary())], ["node", "shingles"])

    firsts = marked.join(wanted.select(F.col("node").alias("_n")), F.col("node") == F.col("_n"), "left_semi")
    ids = firsts.groupBy("node").agg(F.min("doc_id").alias("_id"))
    small = packed(docs.select("doc_id", "text"))
    named = small.join(ids.where("_id is not null").select("_id").distinct(), F.col("doc_id") == F.col("_id"), "left_semi")
    bare = small.where("doc_id is null")
    sets = named.unionByName(bare).select("text").mapInArrow(tidy(with_node), "node long, shingles binary")
    return sets.groupBy("node").agg(F.min("shingles").alias("shingles"))


def _verified(pairs: DataFrame, sets: DataFrame, at_least: float) -> DataFrame:
    """The pairs (a, b) whose shingle sets are at least so similar."""
    longest = F.lit(at_least) * F.greatest(F.length("x"), F.length("y")) - F.lit(1e-9)
    left = sets.select(F.col("node").alias("_a"), F.col("shingles").alias("x"))
    right = sets.select(F.col("node").alias("_b"), F.col("shingles").alias("y"))
    both = pairs.join(left, F.col("a") == F.col("_a")).join(right, F.col("b") == F.col("_b")).where(F.least(F.length("x"), F.length("y")) >= longest).select("a", "b", "x", "y")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, CHUNK):
                b = whole.slice(at, CHUNK)
                good = []
                for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                    x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                    common = len(np.intersect1d(x, y, assume_unique=True))
                    good.append(common >= at_least * (len(x) + len(y) - common) - 1e-9)
                yield b.select([0, 1]).filter(pa.array(good, pa.bool_()))

    return both.mapInArrow(tidy(rows), "a long, b long")


def _balls(nodes: DataFrame) -> DataFrame:
    """(a, b): nodes whose fingerprints are equal or within the radius, every one linked to a least one."""
    firsts = written(nodes.groupBy("fp").agg(F.min("node").alias("first")), "fingerprints")
    same = nodes.join(firsts.withColumnRenamed("fp", "_fp"), F.col("fp") == F.col("_fp")).where("node != first").select(F.col("first").alias("a"), F.col("node").alias("b"))
    left = firsts.select(F.col("fp").alias("_a"), F.col("first").alias("x"))
    right = firsts.select(F.col("fp").alias("_b"), F.col("first").alias("y"))
    near = simhash.links(firsts.select("fp")).join(left, F.col("a") == F.col("_a")).join(right, F.col("b") == F.col("_b"))
    return same.unionAll(near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")))


def _stars(held: DataFrame) -> DataFrame:
    """(a, b): the members of every bucket beside its least one."""
    least = written(held.groupBy("key").agg(F.min("node").alias("a")).withColumnRenamed("key", "_key"), "pivots")
    return held.join(least, F.col("key") == F.col("_key")).where("node > a").select("a", F.col("node").alias("b"))


def blocks(held: DataFrame) -> DataFrame:
    """(block, node): blocks in which any two mates of buckets with several components meet.

    A bucket's nodes are dealt into about equal parts, and two parts make a block; blocks of the same
    nodes, of which like texts make one a band, are one block.
    """
    parts = F.ceil(F.greatest(F.count("*") / F.lit(BLOCK_NODES), F.sum("size") / F.lit(BLOCK_SHINGLES))).cast("int")
    mixed = written(held.groupBy(F.col("key").alias("_key")).agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), parts.alias("parts")).where("lo < hi").select("_key", "parts"), "mixed")
    part = F.pmod(F.xxhash64("node"), F.col("parts")).cast("int")
    dealt = held.join(mixed, F.col("key") == F.col("_key")).withColumn("part", part).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    met = dealt.groupBy("key", F.least("part", "other").alias("lo"), F.greatest("part", "other").alias("hi")).agg(F.array_sort(F.collect_set(F.struct("node", "comp"))).alias("members"))
    several = met.where(F.size(F.array_distinct("members.comp")) > 1)
    return several.groupBy(F.xxhash64("members.node").alias("block")).agg(F.first("members.node").alias("n")).select("block", F.explode("n").alias("node"))


def like_pairs(sets: list[np.ndarray], comps: np.ndarray, at_least: float) -> list[tuple[int, int]]:
    """Pairs of components that have like members among these sorted sets."""
    size = np.array([len(x) for x in sets], np.int64)
    i, j = np.nonzero(comps[:, None] < comps)
    able = np.minimum(size[i], size[j]) >= at_least * np.maximum(size[i], size[j]) - 1e-9
    i, j = i[able], j[able]
    if not len(i):
        return []
    _, of, n = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = n > 1  # shingles of one member alone are in no intersection
    of, row = (np.cumsum(shared) - 1)[of[shared[of]]], np.repeat(np.arange(len(sets)), size)[shared[of]]
    order = np.argsort(of, kind="stable")
    of, row = of[order], row[order]
    both = np.zeros((len(sets), len(sets)), np.float32)
    step = max(1, CELLS // len(sets))
    for lo in range(0, int(shared.sum()), step):
        x, y = np.searchsorted(of, [lo, lo + step])
        there = np.zeros((len(sets), int(of[y - 1]) - lo + 1), np.float32)
        there[row[x:y], of[x:y] - lo] = 1
        both += there @ there.T
    common = both[i, j]
    good = common >= at_least * (size[i] + size[j] - common) - 1e-4
    return sorted(set(zip(comps[i[good]].tolist(), comps[j[good]].tolist(), strict=True)))


def _compared(blocks: DataFrame, sets: DataFrame, roots: DataFrame, at_least: float) -> DataFrame:
    """(a, b): components that have like members in a block."""
    rooted = sets.join(roots, F.col("node") == F.col("_node"), "left").select(F.col("node").alias("_n"), F.coalesce("root", "node").alias("comp"), "shingles")
    full = blocks.join(rooted, F.col("node") == F.col("_n")).select("block", "comp", "shingles")

    def links(group: pa.Table) -> pa.Table:
        members = [np.frombuffer(x, np.uint64) for x in group.column("shingles").to_pylist()]
        found = like_pairs(members, group.column("comp").to_numpy(), at_least)
        return pa.table({"a": pa.array([x for x, _ in found], pa.int64()), "b": pa.array([y for _, y in found], pa.int64())})

    return full.groupBy("block").applyInArrow(links, "a long, b long")


def classes(docs: DataFrame, at_least: float = SIMILAR) -> tuple[DataFrame, DataFrame]:
    """(doc_id, fp) of every row, and (fp, component_id, root) of every distinct fp, its shingle set's node."""
    marked = written(_marked(docs), "marked")
    nodes = written(marked.groupBy("node").agg(F.min("doc_id").alias("first_id"), F.first("size").alias("size"), F.first("fp").alias("fp"), F.first("bands").alias("bands")), "nodes")
    keyed = nodes.select(F.explode("bands").alias("key"), "node", "size")
    shared = keyed.groupBy(F.col("key").alias("_key")).agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo < hi").select("_key")
    held = written(keyed.join(written(shared, "bucket-keys"), F.col("key") == F.col("_key"), "left_semi"), "buckets")
    pairs = written(_balls(nodes).unionAll(_stars(held)).distinct(), "pairs")
    wanted = held.select("node").unionAll(pairs.select("a")).unionAll(pairs.select("b")).distinct()
    sets = written(_sets(docs, marked.select("doc_id", "node"), wanted), "shingles")
    roots = written(components(_verified(pairs, sets, at_least)).withColumnRenamed("node", "_node"), "roots")
    comp = F.coalesce("root", "node")
    met = written(blocks(held.join(roots, F.col("node") == F.col("_node"), "left").select("key", "node", "size", comp.alias("comp"))), "blocks")
    more = written(components(_compared(met, sets, roots, at_least)).select(F.col("node").alias("_root"), F.col("root").alias("_top")), "roots")
    rooted = nodes.select("node", "first_id").join(roots, F.col("node") == F.col("_node"), "left").select("node", "first_id", comp.alias("_comp"))
    rooted = rooted.join(more, F.col("_comp") == F.col("_root"), "left").select(F.col("node").alias("fp"), "first_id", F.coalesce("_top", "_comp").alias("root"))
    ids = rooted.groupBy(F.col("root").alias("of")).agg(F.min("first_id").alias("component_id"))
    return marked.select("doc_id", F.col("node").alias("fp")), rooted.join(ids, F.col("root") == F.col("of")).select("fp", "component_id", "root")


def keep_one(docs: DataFrame, at_least: float = SIMILAR) -> DataFrame:
    """One row of ``docs`` for each component, with all columns, chosen as ``simhash.keep_one`` does."""
    marked, of = classes(docs, at_least)
    return simhash.one_each(docs, marked, written(of, "classes"), text_nodes)
