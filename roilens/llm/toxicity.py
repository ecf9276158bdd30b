"""Toxicity by multiple-instance learning: a document is a bag of sentences.

A sentence's score is a logistic function of its words and word beginnings; a document is toxic with
probability 1 - prod(1 - p(sentence)) (noisy-or), and only document labels teach.  The trained weights
then locate offending sentences.  Sentences end at '.', '!', '?' and line feeds.  Null and empty
texts hold no sentence: their score is 0, the noisy-or of nothing.

Fitting uses about ``SAMPLE`` labelled rows of the teaching folds; features kept are those seen in
at least ``MIN_DOCS`` sampled documents.  Every whole text is scored in one pass without a shuffle.
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
from .textscan import Scan, keyed, slices

SAMPLE = 6000
MIN_DOCS = 4
HELD_OUT = (5, 0)
THRESHOLD = 0.5
SEED = 31
PREFIXES = (4, 5, 6)
TRAIN_SLICE, SKETCH_BITS = 1 << 20, 22

_LETTER = np.zeros(256, bool)
_LETTER[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_STOP = np.zeros(256, bool)
_STOP[[ord(c) for c in ".!?\n"]] = True


def sentence_features(texts: pa.Array) -> tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray, Scan]:
    """(number of sentences, their documents, their byte ends, sentence of each feature, feature keys, scan).

    Words here are runs of letters, digits and non-ASCII bytes, lower-cased in ASCII; features are the
    hashes of whole words and of their first ``PREFIXES`` bytes.
    """
    s = Scan(texts)
    letter = _LETTER[s.data]
    edge = np.flatnonzero(letter[1:] != letter[:-1]) + 1
    if len(s.data) and letter[0]:
        edge = np.concatenate(([0], edge))
    starts, ends = edge[0::2], edge[1::2]
    stops = np.flatnonzero(_STOP[s.data])
    sentence = np.searchsorted(stops, starts, "left")
    used, index = np.unique(sentence, return_inverse=True)
    docs = np.searchsorted(s.offsets, stops[used], "right") - 1 if len(used) else np.empty(0, np.int64)
    keys, owner = [s.hashes(starts, ends, lower=True)], [index]
    for k in PREFIXES:
        long = np.flatnonzero(ends - starts > k)
        keys.append(s.hashes(starts[long], starts[long] + k, lower=True) + np.uint64(k))
        owner.append(index[long])
    return len(used), docs, stops[used] if len(used) else stops[:0], np.concatenate(owner), np.concatenate(keys), s


@dataclass
class BagModel:
    """Sorted feature keys, their weights, and the bias of every sentence."""

    keys: np.ndarray
    weights: np.ndarray
    bias: float

    def sentence_scores(self, n: int, owner: np.ndarray, keys: np.ndarray) -> np.ndarray:
        z = np.full(n, self.bias)
        if len(self.keys) and len(keys):
            at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
            hit = self.keys[at] == keys
            z += np.bincount(owner[hit], self.weights[at[hit]], n)
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))

    def score(self, texts: pa.Array) -> np.ndarray:
        out = [np.zeros(0)]
        for a, b in slices(texts):
            part = texts.slice(a, b - a)
            n, docs, _, owner, keys, _ = sentence_features(part)
            p = self.sentence_scores(n, owner, keys)
            out.append(1 - np.exp(np.bincount(docs, np.log1p(-np.minimum(p, 1 - 1e-12)), len(part))))
        return np.concatenate(out)

    def worst(self, texts: pa.Array) -> list[tuple[float, str] | None]:
        """For every text its highest sentence score and that sentence (None without words)."""
        found: list[tuple[float, str] | None] = []
        for a, b in slices(texts):
            part = texts.slice(a, b - a)
            n, docs, stop, owner, keys, s = sentence_features(part)
            p = self.sentence_scores(n, owner, keys)
            best: dict[int, int] = {}
            for i in np.argsort(-p, kind="stable").tolist():
                best.setdefault(int(docs[i]), i)
            stops = np.flatnonzero(_STOP[s.data])
            for d in range(len(part)):
                i = best.get(d)
                if i is None:
                    found.append(None)
                    continue
                j = int(np.searchsorted(stops, stop[i]))
                begin = max(int(stops[j - 1]) + 1 if j else 0, int(s.offsets[d]))
                found.append((float(p[i]), s.data[begin : stop[i]].tobytes().decode("utf-8", "replace").strip()))
        return found


def train(texts: pa.Array, y: np.ndarray, steps: int = 150, rate: float = 0.15, ridge: float = 2e-4, sparse: float = 2e-3) -> BagModel:
    """Fit by full-batch Adam on the noisy-or log-likelihood with ridge and soft-threshold shrinkage."""
    parts = list(slices(texts, TRAIN_SLICE))
    # first pass: a counting sketch of documents by feature, which no rare feature passes but by collision
    sketch = np.zeros(1 << SKETCH_BITS, np.int32)
    low = np.uint64((1 << SKETCH_BITS) - 1)
    for a, b in parts:
        _, d, _, o, k, _ = sentence_features(texts.slice(a, b - a))
        _, once = np.unique(keyed(k, d[o]), return_index=True)
        sketch += np.bincount((k[once] & low).astype(np.int64), minlength=len(sketch)).astype(np.int32)
    docs, owners, keys, seen, base = [], [], [], [], 0
    for a, b in parts:
        n, d, _, o, k, _ = sentence_features(texts.slice(a, b - a))
        often = sketch[(k & low).astype(np.int64)] >= MIN_DOCS
        o, k = o[often], k[often]
        _, once = np.unique(keyed(k, d[o]), return_index=True)
        docs.append((d + a).astype(np.int32))
        owners.append((o + base).astype(np.int32))
        keys.append(k)
        seen.append(k[once])
        base += n
    if not base or not y.any() or y.all():
        share = float(np.clip(y.mean(), 1e-3, 1 - 1e-3)) if len(y) else 1e-3
        return BagModel(np.empty(0, np.uint64), np.empty(0), float(np.log(share / (1 - share))) - 3.0)
    doc, owner, key = np.concatenate(docs), np.concatenate(owners), np.concatenate(keys)
    known, df = np.unique(np.concatenate(seen), return_counts=True)
    known = known[df >= MIN_DOCS]
    at = np.minimum(np.searchsorted(known, key), len(known) - 1) if len(known) else np.zeros(len(key), int)
    hit = known[at] == key if len(known) else np.zeros(len(key), bool)
    owner, col = owner[hit], at[hit].astype(np.int32)
    del docs, owners, keys, seen, key, at, hit
    n_docs, n_features = len(y), len(known)
    w, bias = np.zeros(n_features), -5.0
    m, v, mb, vb = np.zeros(n_features), np.zeros(n_features), 0.0, 0.0
    for t in range(1, steps + 1):
        z = np.clip(bias + np.bincount(owner, w[col], base), -30, 30)
        p = 1 / (1 + np.exp(-z))
        log_none = np.bincount(doc, np.log1p(-np.minimum(p, 1 - 1e-12)), n_docs)
        none = np.exp(log_none)
        # d loss / d z of a sentence: p for clean documents, -p * none / (1 - none) for toxic ones
        slope = np.where(y > 0, -none / np.maximum(1 - none, 1e-9), 1.0)[doc] * p / n_docs
        g = np.bincount(col, slope[owner], n_features) + ridge * w / n_docs
        gb = slope.sum()
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        mb, vb = 0.9 * mb + 0.1 * gb, 0.999 * vb + 0.001 * gb * gb
        c1, c2 = 1 - 0.9**t, 1 - 0.999**t
        w = w - rate * (m / c1) / (np.sqrt(v / c2) + 1e-9) * (np.abs(g) * n_docs > 0.3)
        w = np.sign(w) * np.maximum(np.abs(w) - sparse, 0)
        bias -= rate * (mb / c1) / (np.sqrt(vb / c2) + 1e-9)
    used = np.abs(w) > 1e-6
    return BagModel(known[used], w[used], float(bias))


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> BagModel:
    """Train on about ``sample`` labelled whole texts outside the held-out fold (a bounded collect)."""
    rows = labelled_sample(docs, labels, "toxic", fold("doc_id", HELD_OUT[0]) != HELD_OUT[1], sample, SEED)
    got = rows.select("doc_id", "text", "_label").toArrow().sort_by([("doc_id", "ascending"), ("text", "ascending")])
    return train(got["text"].combine_chunks(), got["_label"].to_numpy())


def score(docs: DataFrame, model: BagModel) -> DataFrame:
    """doc_id, held_out, score, predicted, and the worst sentence of documents predicted toxic."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = model.score(b.column(2))
            bad = np.flatnonzero(s >= THRESHOLD)
            found: list[str | None] = [None] * len(s)
            for i, x in zip(bad.tolist(), model.worst(b.column(2).take(pa.array(bad))), strict=True):
                found[i] = x[1] if x else None
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(s), pa.array(found, pa.string())], ["doc_id", "held_out", "score", "worst_sentence"])

    base = docs.select("doc_id", (fold("doc_id", HELD_OUT[0]) == HELD_OUT[1]).alias("held_out"), "text")
    schema = T.StructType([base.schema["doc_id"], base.schema["held_out"], T.StructField("score", T.DoubleType()), T.StructField("worst_sentence", T.StringType())])
    return base.mapInArrow(rows, schema).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))
