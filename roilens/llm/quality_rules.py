"""Quality rules: exact document statistics, base rules, and gradient-boosted trees over them.

Trees are grown by second-order boosting of the logistic loss on histogram bins, with monotone
constraints on chosen features (more symbols, repeats or duplicate lines never raise a score), then
flattened into numpy node arrays that score a whole batch level by level.  A null or empty text has
no words, so the base rules fail it.  Fitting uses about ``SAMPLE`` labelled rows of the teaching
folds; every document is counted and judged, in one pass without a shuffle.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fold, labelled_sample
from .textscan import Scan, keyed, repeated, slices

SAMPLE = 12000
SEED = 23
KEEP_AT = 0.5
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Derived inputs of the trees and the direction a score may move with them (0: free).
INPUTS = (
    ("log_words", 0), ("mean_word_chars", 0), ("symbols_per_word", -1), ("dup_lines_per_word", -1),
    ("repeat_share", -1), ("upper_share", -1), ("marks_per_word", -1), ("same_next_share", -1),
)

_SYMBOL = np.zeros(256, np.uint8)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = 1
_SYMBOL[65:91] = 2
_SYMBOL[ord("!")] = 3
_CHAR = np.ones(256, bool)
_CHAR[128:192] = False  # UTF-8 continuation bytes


def statistics(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Exact ``COUNTS`` (int64) and the trees' ``INPUTS`` (float64), one row a document."""
    parts = [_slice_statistics(texts.slice(a, b - a)) for a, b in slices(texts)]
    if not parts:
        return np.zeros((0, len(COUNTS)), np.int64), np.zeros((0, len(INPUTS)))
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _slice_statistics(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    s = Scan(texts)
    words = s.words_per_doc()
    chars = np.concatenate(([0], np.cumsum(_CHAR[s.data])))
    word_chars = np.bincount(s.word_doc, chars[s.ends] - chars[s.starts], s.n).astype(np.int64)
    kinds = s.byte_counts(_SYMBOL, 4)
    a, b = s.lines()
    line_doc = np.searchsorted(s.offsets, a, "right") - 1
    again, _ = repeated(keyed(s.hashes(a, b), line_doc))
    dup_lines = np.bincount(line_doc[again], minlength=s.n)
    wh = s.word_hashes()
    at, h = s.windows(wh, 5)
    _, twice = repeated(keyed(h, s.word_doc[at]))
    covered = np.zeros(len(wh) + 1, np.int64)
    hit = at[twice]
    np.add.at(covered, hit, 1)
    np.add.at(covered, np.minimum(hit + 5, len(wh)), -1)
    inside = np.cumsum(covered)[:-1] > 0
    repeats = np.bincount(s.word_doc[inside], minlength=s.n)
    counts = np.column_stack([words, word_chars, kinds[:, 1], dup_lines, repeats]).astype(np.int64)
    some = np.maximum(words, 1)
    same = np.flatnonzero((wh[1:] == wh[:-1]) & (s.word_doc[1:] == s.word_doc[:-1]))
    inputs = np.column_stack(
        [
            np.log1p(words), word_chars / some, kinds[:, 1] / some, dup_lines / some, repeats / some,
            kinds[:, 2] / np.maximum(word_chars, 1), kinds[:, 3] / some, np.bincount(s.word_doc[same], minlength=s.n) / some,
        ]
    )
    return counts, inputs


def base_failed(counts: np.ndarray) -> np.ndarray:
    return (counts[:, 0] < 10) | (100 * counts[:, 4] > 20 * counts[:, 0])


@dataclass
class Trees:
    """Boosted trees as flat arrays: every tree is a complete binary tree of ``depth`` levels.

    ``feature`` and ``cut`` hold inner nodes in level order, ``leaf`` the outputs; a row goes right
    where its value is over the cut.
    """

    depth: int
    feature: np.ndarray
    cut: np.ndarray
    leaf: np.ndarray
    start: float = 0.0

    def raw(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.start)
        rows = np.arange(len(x))
        for f, c, leaf in zip(self.feature, self.cut, self.leaf, strict=True):
            node = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                node = 2 * node + 1 + (x[rows, f[node]] > c[node])
            total += leaf[node - len(f)]
        return total

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(x), -30, 30)))


def grow(x: np.ndarray, y: np.ndarray, monotone: tuple[int, ...], rounds: int = 60, depth: int = 3, rate: float = 0.15, bins: int = 64, ridge: float = 1.0) -> Trees:
    """Boost complete trees on quantile bins.

    A split on a constrained feature is refused if its children's values point the wrong way; the
    midpoint of the two values then bounds every later value on either side, so that constraints
    hold over whole trees and hence over their sum.
    """
    n_inner = 2**depth - 1
    trees = Trees(depth, np.zeros((rounds, n_inner), np.int64), np.full((rounds, n_inner), np.inf), np.zeros((rounds, n_inner + 1)))
    if not len(y):
        return trees
    share = np.clip(y.mean(), 1e-3, 1 - 1e-3)
    trees.start = float(np.log(share / (1 - share)))
    cuts = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1])) for c in x.T]
    binned = np.column_stack([np.searchsorted(c, v, "left") for c, v in zip(cuts, x.T, strict=True)])  # value > cut[b] iff bin > b
    raw = np.full(len(y), trees.start)
    for t in range(rounds):
        p = 1 / (1 + np.exp(-raw))
        g, h = y - p, p * (1 - p)
        node = np.zeros(len(y), np.int64)
        low, high = np.full(2 * n_inner + 1, -np.inf), np.full(2 * n_inner + 1, np.inf)
        for k in range(n_inner):
            rows = np.flatnonzero(node == k)
            best = (1e-6, -1, 0, 0.0, 0.0)
            sg, sh = g[rows].sum(), h[rows].sum()
            for f in range(x.shape[1]) if len(rows) > 20 else ():
                size = len(cuts[f]) + 1
                gl = np.cumsum(np.bincount(binned[rows, f], g[rows], size))[:-1]
                hl = np.cumsum(np.bincount(binned[rows, f], h[rows], size))[:-1]
                vl = np.clip(gl / (hl + ridge), low[k], high[k])
                vr = np.clip((sg - gl) / (sh - hl + ridge), low[k], high[k])
                gain = 2 * gl * vl - (hl + ridge) * vl**2 + 2 * (sg - gl) * vr - (sh - hl + ridge) * vr**2 - sg**2 / (sh + ridge)
                ok = (hl > 0.5) & (sh - hl > 0.5) & ((vr - vl) * monotone[f] >= 0)
                gain = np.where(ok, gain, -np.inf)
                if len(gain) and gain.max() > best[0]:
                    b = int(gain.argmax())
                    best = (gain[b], f, b, vl[b], vr[b])
            left, right = 2 * k + 1, 2 * k + 2
            low[[left, right]], high[[left, right]] = low[k], high[k]
            if best[1] < 0:
                node[rows] = left
                continue
            _, f, b, vl, vr = best
            trees.feature[t, k], trees.cut[t, k] = f, cuts[f][b]
            node[rows] = np.where(binned[rows, f] > b, right, left)
            if monotone[f]:
                up, mid = (right, left) if monotone[f] > 0 else (left, right), (vl + vr) / 2
                low[up[0]], high[up[1]] = max(low[up[0]], mid), min(high[up[1]], mid)
        leaf = node - n_inner
        value = np.bincount(leaf, g, n_inner + 1) / (np.bincount(leaf, h, n_inner + 1) + ridge)
        trees.leaf[t] = rate * np.clip(value, low[n_inner:], high[n_inner:])
        raw += trees.leaf[t][leaf]
    return trees


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Trees:
    """Trees from about ``sample`` labelled rows outside the held-out fold."""
    rows = labelled_sample(docs, labels, "quality", fold("doc_id", 4) != 2, sample, SEED)

    def inputs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(list(statistics(b.column(0))[1]), pa.list_(pa.float64())), b.column(1)], ["x", "y"])

    got = rows.select("text", "_label").mapInArrow(inputs, "x array<double>, y int").collect()
    x = np.array([r.x for r in got]).reshape(-1, len(INPUTS))
    y = np.array([r.y for r in got], float)
    order = np.lexsort([y, *x.T[::-1]])
    return grow(x[order], y[order], tuple(m for _, m in INPUTS))


def judge(docs: DataFrame, trees: Trees) -> DataFrame:
    """doc_id, the exact counts, base_failed, tree_score and kept for every row of ``docs``."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            counts, x = statistics(b.column(1))
            failed, s = base_failed(counts), trees.score(x)
            yield pa.RecordBatch.from_arrays([b.column(0), *map(pa.array, counts.T), pa.array(failed), pa.array(~failed & (s >= KEEP_AT)), pa.array(s)], names)

    names = ["doc_id", *COUNTS, "base_failed", "kept", "tree_score"]
    base = docs.select("doc_id", "text")
    schema = T.StructType([base.schema["doc_id"], *(T.StructField(c, T.LongType()) for c in COUNTS), T.StructField("base_failed", T.BooleanType()), T.StructField("kept", T.BooleanType()), T.StructField("tree_score", T.DoubleType())])
    return base.mapInArrow(rows, schema)
