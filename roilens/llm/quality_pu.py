"""Quality classifier by positive-unlabelled learning with the non-negative unbiased risk.

Trusted positives are rows labelled 1 in the teaching folds; the unlabelled set is web text taken
from all documents of those folds, whatever it holds.  The class prior is estimated from how the
scores of a first model spread over both sets, then a small network minimises

    prior * E_pos[l(f, +1)] + max(0, E_unl[l(f, -1)] - prior * E_pos[l(f, -1)])

and the sigmoid of its output estimates the probability of label 1.  Inputs are statistics of the
whole text only.  Null and empty texts have the statistics of no words and get a score like any other.

Fitting uses a bounded, documented sample (``POSITIVES``, ``UNLABELLED`` rows in expectation); every
document is scored, in one pass over the table without a shuffle.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fold, labelled_sample, unit_hash
from .textscan import Scan, keyed, repeated, slices, tidy

POSITIVES = 8000
UNLABELLED = 16000
HELD_OUT = (4, 2)
THRESHOLD = 0.7
SEED = 11

FEATURES = (
    "log_words", "mean_word", "upper", "digit", "symbol", "pipe", "mark", "other_punctuation",
    "non_ascii", "distinct_words", "repeat_next", "repeat_trigram", "dup_lines", "line_words", "short",
)

# byte classes: 0 lower and space, 1 upper, 2 digit, 3 symbols, 4 bar, 5 exclamation, 6 other, 7 non-ASCII
_CLASS = np.zeros(256, np.uint8)
_CLASS[65:91] = 1
_CLASS[48:58] = 2
for _c in range(33, 127):
    if not chr(_c).isalnum():
        _CLASS[_c] = 6
_CLASS[[ord(c) for c in "#*$%&<>@^~=_\\{}[]"]] = 3
_CLASS[ord("|")] = 4
_CLASS[ord("!")] = 5
_CLASS[128:] = 7


def features(texts: pa.Array) -> np.ndarray:
    """documents x ``FEATURES`` as float64, from whole texts."""
    parts = [_slice_features(texts.slice(a, b - a)) for a, b in slices(texts)]
    return np.concatenate(parts) if parts else np.zeros((0, len(FEATURES)))


def _slice_features(texts: pa.Array) -> np.ndarray:
    s = Scan(texts)
    words = s.words_per_doc()
    some = np.maximum(words, 1)
    counts = s.byte_counts(_CLASS, 8)
    length = np.bincount(s.word_doc, s.ends - s.starts, s.n)
    wh = s.word_hashes()
    again, _ = repeated(keyed(wh, s.word_doc))
    next_same = np.flatnonzero((wh[1:] == wh[:-1]) & (s.word_doc[1:] == s.word_doc[:-1]))
    at, tri = s.windows(wh, 3)
    tri_again, _ = repeated(keyed(tri, s.word_doc[at]))
    a, b = s.lines()
    line_doc = np.searchsorted(s.offsets, a, "right") - 1
    line_again, _ = repeated(keyed(s.hashes(a, b), line_doc))
    n_lines = np.maximum(np.bincount(line_doc, minlength=s.n), 1)
    chars = np.maximum(length, 1)
    out = np.column_stack(
        [
            np.log1p(words),
            length / some,
            counts[:, 1] / chars,
            counts[:, 2] / chars,
            counts[:, 3] / some,
            counts[:, 4] / some,
            counts[:, 5] / some,
            counts[:, 6] / some,
            counts[:, 7] / chars,
            np.bincount(s.word_doc[again], minlength=s.n) / some,
            np.bincount(s.word_doc[next_same], minlength=s.n) / some,
            np.bincount(s.word_doc[at[tri_again]], minlength=s.n) / some,
            np.bincount(line_doc[line_again], minlength=s.n) / n_lines,
            np.log1p(words / n_lines),
            words < 5,
        ]
    )
    return np.where(np.isfinite(out), out, 0.0)


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(z, -30, 30)))


class PUNetwork:
    """One hidden layer of tanh units; ``fit`` follows the non-negative risk by full-batch Adam."""

    def __init__(self, n_in: int, hidden: int = 12, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.w = [rng.normal(0, n_in**-0.5, (n_in, hidden)), np.zeros(hidden), rng.normal(0, hidden**-0.5, hidden), np.zeros(1)]
        self.centre, self.scale, self.prior = np.zeros(n_in), np.ones(n_in), 0.5

    def _forward(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = np.tanh(x @ self.w[0] + self.w[1])
        return h, h @ self.w[2] + self.w[3][0]

    def _inputs(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.centre) / self.scale, -6, 6)

    def score(self, x: np.ndarray) -> np.ndarray:
        return _sigmoid(self._forward(self._inputs(x))[1])

    def fit(self, pos: np.ndarray, unl: np.ndarray, prior: float, steps: int = 500, rate: float = 0.02, decay: float = 1e-3) -> list[float]:
        """Returns the risk after each step.  Where the negative part falls below zero, the step raises it instead."""
        both = np.concatenate([pos, unl])
        self.centre, self.scale = both.mean(0), both.std(0) + 1e-6
        self.prior = prior
        x, n_pos = self._inputs(both), len(pos)
        m, v = [np.zeros_like(w) for w in self.w], [np.zeros_like(w) for w in self.w]
        risks = []
        for t in range(1, steps + 1):
            h, f = self._forward(x)
            p = _sigmoid(f)
            softplus = np.logaddexp(0, f)  # loss of a negative; of a positive it is softplus - f
            pos_part = prior * (softplus - f)[:n_pos].mean()
            neg_part = softplus[n_pos:].mean() - prior * softplus[:n_pos].mean()
            d_neg = np.concatenate([-prior * p[:n_pos] / n_pos, p[n_pos:] / (len(x) - n_pos)])
            if neg_part >= 0:
                g = d_neg
                g[:n_pos] += prior * (p[:n_pos] - 1) / n_pos
            else:
                g = -d_neg
            risks.append(pos_part + max(0.0, neg_part))
            back = np.outer(g, self.w[2]) * (1 - h**2)
            grads = [x.T @ back, back.sum(0), h.T @ g, np.array([g.sum()])]
            for k, d in enumerate(grads):
                d = d + decay * self.w[k] * (k in (0, 2))
                m[k] = 0.9 * m[k] + 0.1 * d
                v[k] = 0.999 * v[k] + 0.001 * d * d
                self.w[k] = self.w[k] - rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
        return risks


def class_prior(pos_scores: np.ndarray, unl_scores: np.ndarray, delta: float = 0.1) -> float:
    """Share of positives among the unlabelled, by the best top bin.

    If some region of high scores holds positives only, the share of the unlabelled above a
    threshold over the share of the positives above it tends to the prior; the threshold with the
    smallest upper confidence bound is taken.
    """
    pos, unl = np.sort(pos_scores), np.sort(unl_scores)
    cuts = np.quantile(pos, np.linspace(0, 0.95, 96))
    q_pos = 1 - np.searchsorted(pos, cuts, "left") / len(pos)
    q_unl = 1 - np.searchsorted(unl, cuts, "left") / len(unl)
    slack = np.sqrt(np.log(4 / delta) / 2) * (len(pos) ** -0.5 + len(unl) ** -0.5)
    best = np.argmin((q_unl + slack) / q_pos)
    return float(np.clip(q_unl[best] / q_pos[best], 0.05, 0.98))


def train(pos: np.ndarray, unl: np.ndarray) -> PUNetwork:
    """First model at prior 0.5 on half the rows, prior from its scores of the other half, then the model at that prior.

    With no positives or no unlabelled rows nothing can be learnt: the model then scores 0.5.
    """
    net = PUNetwork(len(FEATURES))
    if not len(pos) or not len(unl):
        net.w = [np.zeros_like(w) for w in net.w]
        return net
    if len(pos) < 2 or len(unl) < 2:
        prior = 0.5
    else:
        net.fit(pos[::2], unl[::2], 0.5, steps=150)
        prior = class_prior(net.score(pos[1::2]), net.score(unl[1::2]))
    net = PUNetwork(len(FEATURES))
    net.fit(pos, unl, prior)
    return net


def _feature_rows(df: DataFrame) -> DataFrame:
    """(x array, y) of sampled rows (text, _label)."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = features(b.column(0))
            yield pa.RecordBatch.from_arrays([pa.array(list(x), pa.list_(pa.float64())), b.column(1)], ["x", "y"])

    return df.select("text", F.col("_label").alias("y")).mapInArrow(tidy(rows), "x array<double>, y int")


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, positives: int = POSITIVES, unlabelled: int = UNLABELLED) -> PUNetwork:
    """Train on bounded samples of the teaching folds."""
    teach = fold("doc_id", HELD_OUT[0]) != HELD_OUT[1]
    pos = labelled_sample(docs, labels, "quality", teach & (F.col("quality") == 1), positives, SEED)
    n = docs.count()
    share = min(1.0, unlabelled / n) if n else 0.0
    unl = docs.where(teach & (unit_hash("doc_id", seed=SEED + 1) < share)).select("doc_id", "text", F.lit(0).alias("_label"))
    got = _feature_rows(pos.unionByName(unl)).collect()
    x = np.array([r.x for r in got]).reshape(-1, len(FEATURES))
    y = np.array([r.y for r in got], int)
    order = np.lexsort(x.T[::-1])  # the same model whatever order the rows came in
    x, y = x[order], y[order]
    return train(x[y == 1], x[y == 0])


def score(docs: DataFrame, model: PUNetwork) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of ``docs``, repeated rows included."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(model.score(features(b.column(2))))], ["doc_id", "held_out", "score"])

    base = docs.select("doc_id", (fold("doc_id", HELD_OUT[0]) == HELD_OUT[1]).alias("held_out"), "text")
    schema = T.StructType([base.schema["doc_id"], base.schema["held_out"], T.StructField("score", T.DoubleType())])
    return base.mapInArrow(tidy(rows), schema).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def keep_good(docs: DataFrame, model: PUNetwork, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that score at least ``threshold``, with all their columns."""
    at = docs.columns.index("text")

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array(model.score(features(b.column(at))) >= threshold))

    return docs.mapInArrow(tidy(rows), docs.schema)
