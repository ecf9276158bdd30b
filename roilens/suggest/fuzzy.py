"""Fuzzy highlights: all regions of a session at once, centroids refined until they rest.

Relevance, cohesiveness (mean similarity to a region's points, from facet counts) and representativeness
(distance to the other centroids) are weighed into one score; ``topk_mean`` moves a centroid to the
membership-weighted mean of its best points, ``cmeans`` is fuzzy c-means with relevance as weight.
``highlight`` takes a row for each match; ``inside.fuzzy_highlight`` gives the same from ``Crowd``.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..geo import polygon
from ..params import Params
from ..storage import written

SCHEMA = "session_id long, roi_id int, rank int, poi_id long, relevance double, membership double, score double, k_prime int, iterations int, shift double, objective double"
KINDS = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.int32(), pa.int32(), pa.float64(), pa.float64())


def memberships_of(d: np.ndarray, m: float = 2.0) -> np.ndarray:
    """regions x points memberships from distances; a point on a centroid belongs to it alone."""
    zero = d <= 0
    inv = np.where(zero, 1.0, d) ** (-2.0 / (m - 1))
    u = inv / inv.sum(0)
    on = zero.any(0)
    u[:, on] = zero[:, on] / zero[:, on].sum(0)
    return u


def refine(c: np.ndarray, p: np.ndarray, rel: np.ndarray, coh: np.ndarray, k: np.ndarray, prm: Params) -> tuple[np.ndarray, np.ndarray, np.ndarray, int, float, list[float]]:
    """(centroids, memberships, scores, iterations, last shift, objective of each iteration) for one session."""
    w1, w2, w3 = prm.weights
    z = len(c)
    trace: list[float] = []
    seen: set[bytes] = set()
    shift, it = 0.0, 0
    for it in range(1, prm.max_iter + 1):
        d = np.hypot(c[:, None, 0] - p[None, :, 0], c[:, None, 1] - p[None, :, 1])
        u = memberships_of(d, prm.fuzzifier)
        rep = (d.sum(0)[None, :] - d) / (prm.diagonal * max(1, z - 1))
        s = w1 * rel + w2 * coh + w3 * rep
        new = c.copy()
        if prm.fuzzy == "cmeans":
            weight = u**prm.fuzzifier * np.maximum(rel, 1e-12)
            trace.append(float((weight * d**2).sum()))
            new = weight @ p / weight.sum(1, keepdims=True)
        else:
            owner = u.argmax(0)
            total = 0.0
            for i in range(z):
                mine = np.flatnonzero(owner == i)
                best = mine[np.lexsort([mine, -np.round(s[i, mine], 9)])][: k[i]]
                if len(best):
                    q = u[i, best] ** 2
                    new[i] = q @ p[best] / q.sum()
                    total += s[i, best].sum()
            trace.append(float(total))
        shift = float(np.hypot(*(new - c).T).max())
        c = new
        key = np.round(c, 6).tobytes()
        if shift < prm.tol or key in seen:
            break
        seen.add(key)
    d = np.hypot(c[:, None, 0] - p[None, :, 0], c[:, None, 1] - p[None, :, 1])
    rep = (d.sum(0)[None, :] - d) / (prm.diagonal * max(1, z - 1))
    return c, memberships_of(d, prm.fuzzifier), w1 * rel + w2 * coh + w3 * rep, it, shift, trace


class Crowd:
    """A session's points, in order of their pixels, for ``refine`` without a value for each region and point.

    Distances and memberships are those of pixels.  Relevance and cohesiveness do not change from one
    iteration to the next, so each point keeps its sum for the region that owns its pixel, and only the
    pixels that can hold one of a region's k best points are opened.
    """

    def __init__(self, ids: np.ndarray, x: np.ndarray, y: np.ndarray, codes: np.ndarray, n_codes: int, inside: Sequence[np.ndarray], relevance: Sequence[np.ndarray]):
        """``codes`` number the points' values (below ``n_codes``); each region has the places of its points and their relevance."""
        self.ids = ids
        self.start = np.flatnonzero(np.r_[True, (np.diff(x) != 0) | (np.diff(y) != 0)])
        self.stop = np.append(self.start[1:], len(ids))
        self.pixel = np.repeat(np.arange(len(self.start)), self.stop - self.start)
        self.xy = np.column_stack([x[self.start], y[self.start]]).astype(float)
        self.rel = np.full(len(ids), -np.inf)
        self.cells = codes + np.arange(codes.shape[1]) * n_codes
        self.counts = np.empty((len(inside), codes.shape[1] * n_codes), np.int64)
        for i, (at, rel) in enumerate(zip(inside, relevance, strict=True)):
            self.rel[at] = np.maximum(self.rel[at], rel)
            self.counts[i] = np.bincount(self.cells[at].ravel(), minlength=self.counts.shape[1])
        self.sizes = np.array([codes.shape[1] * len(at) for at in inside])

    def points(self, pixels: np.ndarray) -> np.ndarray:
        """Places of all points of these pixels."""
        n = self.stop[pixels] - self.start[pixels]
        return np.repeat(self.start[pixels] - np.cumsum(n) + n, n) + np.arange(n.sum())

    def fixed(self, at: np.ndarray, region: np.ndarray | int, prm: Params) -> np.ndarray:
        """Weighted relevance and cohesiveness of points for a region, or for one each."""
        which = region[:, None] if isinstance(region, np.ndarray) else region
        return prm.weights[0] * self.rel[at] + prm.weights[1] * (self.counts[which, self.cells[at]].sum(1) / self.sizes[region])

    def distances(self, c: np.ndarray) -> np.ndarray:
        return np.hypot(c[:, None, 0] - self.xy[None, :, 0], c[:, None, 1] - self.xy[None, :, 1])

    def refine(self, c: np.ndarray, k: np.ndarray, prm: Params) -> tuple[np.ndarray, int, float, list[float]]:
        """(centroids, iterations, last shift, objective of each iteration)."""
        z, w3 = len(c), prm.weights[2]
        trace: list[float] = []
        seen: set[bytes] = set()
        shift, it = 0.0, 0
        owner, fixed = np.full(len(self.xy), -1), np.empty(len(self.ids))
        mass = np.add.reduceat(np.maximum(self.rel, 1e-12), self.start)
        for it in range(1, prm.max_iter + 1):
            d = self.distances(c)
            new = c.copy()
            if prm.fuzzy == "cmeans":
                weight = memberships_of(d, prm.fuzzifier) ** prm.fuzzifier * mass
                trace.append(float((weight * d**2).sum()))
                new = weight @ self.xy / weight.sum(1, keepdims=True)
            else:
                before, owner = owner, d.argmin(0)
                at = self.points(np.flatnonzero(owner != before))
                fixed[at] = self.fixed(at, owner[self.pixel[at]], prm)
                rep = w3 * ((d.sum(0) - d[owner, np.arange(len(owner))]) / (prm.diagonal * max(1, z - 1)))
                most = np.round(np.maximum.reduceat(fixed, self.start) + rep, 9)
                total = 0.0
                for i in np.flatnonzero(k).tolist():
                    mine = np.flatnonzero(owner == i)
                    at = self.points(first(mine, most[mine], k[i]))
                    s = fixed[at] + rep[self.pixel[at]]
                    order = np.lexsort([self.ids[at], -np.round(s, 9)])[: k[i]]
                    if len(order):
                        best = self.pixel[at[order]]
                        q = memberships_of(d[:, best], prm.fuzzifier)[i] ** 2
                        new[i] = q @ self.xy[best] / q.sum()
                        total += s[order].sum()
                trace.append(float(total))
            shift = float(np.hypot(*(new - c).T).max())
            c = new
            key = np.round(c, 6).tobytes()
            if shift < prm.tol or key in seen:
                break
            seen.add(key)
        return c, it, shift, trace

    def highlights(self, c: np.ndarray, k: np.ndarray, prm: Params) -> tuple[list[list[tuple]], int, float, float]:
        """((poi_id, relevance, membership, score) of each region's k points of largest membership, iterations, last shift, last objective)."""
        c, it, shift, trace = self.refine(c, k, prm)
        d = self.distances(c)
        u, away, out = memberships_of(d, prm.fuzzifier), d.sum(0), []
        for i, n in enumerate(k.tolist()):
            at = self.points(first(np.arange(len(self.xy)), np.round(u[i], 9), n))
            of = self.pixel[at]
            s = self.fixed(at, i, prm) + prm.weights[2] * ((away[of] - d[i, of]) / (prm.diagonal * max(1, len(c) - 1)))
            order = np.lexsort([self.ids[at], -np.round(s, 9), -np.round(u[i, of], 9)])[:n]
            out.append([(int(self.ids[at[j]]), float(self.rel[at[j]]), float(u[i, of[j]]), float(s[j])) for j in order.tolist()])
        return out, it, shift, trace[-1] if trace else 0.0


def first(at: np.ndarray, value: np.ndarray, k: int) -> np.ndarray:
    """Those of ``at`` with the k largest values and all that equal the last of them; none for k = 0."""
    if not k or len(at) <= k:
        return at[: len(at) * bool(k)]
    return at[value >= np.partition(value, len(at) - k)[len(at) - k]]


def highlight(rois: DataFrame, matched: DataFrame, scored: DataFrame, pois: DataFrame, k_primes: DataFrame, attrs: list[str], params: Params = Params()) -> DataFrame:
    """The k' points of largest membership of every region, found for a session's regions together.

    ``scored`` holds (session_id, poi_id, relevance).  Points that several regions match count once.
    A session's regions come to the kernel beside its points, not on each of them.  ``objective`` is
    that of the last iteration.
    """
    prm = params
    centre = rois.select("session_id", "roi_id", polygon.centroid(F.col("poly")).alias("c")).join(k_primes.select("session_id", "roi_id", "k_prime"), ["session_id", "roi_id"])
    regions = centre.select("session_id", F.col("roi_id").cast("int").alias("roi_id"), F.col("c.x").alias("cx"), F.col("c.y").alias("cy"), F.col("k_prime").cast("int").alias("k_prime"))
    of = matched.groupBy("session_id", "poi_id").agg(F.array_sort(F.collect_set("roi_id")).alias("rois"))
    rel = scored.groupBy("session_id", "poi_id").agg(F.max("relevance").alias("relevance"))
    points = of.join(rel, ["session_id", "poi_id"]).join(pois.select("poi_id", "mx", "my", F.array(*attrs).alias("a")), "poi_id")

    kinds = KINDS
    names = ("session_id", "roi_id", "rank", "poi_id", "relevance", "membership", "score", "k_prime", "iterations", "shift", "objective")

    def kernel(table: pa.Table, beside: pa.Table) -> pa.Table:
        if not table.num_rows or not beside.num_rows:
            return pa.table([pa.array([], kd) for kd in kinds], list(names))
        t = table.sort_by([("poi_id", "ascending")]).to_pylist()
        regs = beside.sort_by([("roi_id", "ascending")]).to_pylist()
        ids = [r["roi_id"] for r in regs]
        c = np.array([[r["cx"], r["cy"]] for r in regs], float)
        k = np.array([r["k_prime"] for r in regs])
        p = np.array([[r["mx"], r["my"]] for r in t], float)
        rl = np.array([r["relevance"] for r in t])
        coh = np.zeros((len(ids), len(t)))
        for i, roi in enumerate(ids):
            inside = [r["a"] for r in t if roi in r["rois"]]
            if inside:
                counts = [{} for _ in inside[0]]
                for a in inside:
                    for n, v in enumerate(a):
                        counts[n][v] = counts[n].get(v, 0) + 1
                coh[i] = [sum(counts[n].get(v, 0) for n, v in enumerate(r["a"])) / (len(counts) * len(inside)) for r in t]
        _, u, s, it, shift, trace = refine(c, p, rl, coh, k, prm)
        last = trace[-1] if trace else 0.0
        out = []
        poi = np.array([r["poi_id"] for r in t])
        for i, roi in enumerate(ids):
            order = np.lexsort([poi, -np.round(s[i], 9), -np.round(u[i], 9)])[: k[i]]
            out += [(t[0]["session_id"], roi, n, int(poi[j]), float(rl[j]), float(u[i, j]), float(s[i, j]), int(k[i]), it, shift, last) for n, j in enumerate(order, 1)]
        cols = list(zip(*out, strict=True)) or [()] * len(names)
        return pa.table([pa.array(x, kd) for x, kd in zip(cols, kinds, strict=True)], list(names))

    return points.groupBy("session_id").cogroup(regions.groupBy("session_id")).applyInArrow(kernel, SCHEMA)


def memberships(points: DataFrame, centroids: DataFrame, m: float = 2.0) -> DataFrame:
    """(session_id, roi_id, poi_id, membership) of points (session_id, poi_id, mx, my) in all of a session's centroids (cx, cy)."""
    d = F.hypot(F.col("mx") - F.col("cx"), F.col("my") - F.col("cy"))
    rows = points.join(centroids, "session_id").withColumn("_d", d)
    w = W.partitionBy("session_id", "poi_id")
    zero = F.sum((F.col("_d") <= 0).cast("int")).over(w)
    inv = F.pow(F.col("_d"), F.lit(-2.0 / (m - 1)))
    u = F.when(zero > 0, F.when(F.col("_d") <= 0, 1.0 / zero).otherwise(0.0)).otherwise(inv / F.sum(inv).over(w))
    return rows.select("session_id", "roi_id", "poi_id", "mx", "my", u.alias("membership"))


def iterate_distributed(points: DataFrame, centroids: DataFrame, params: Params = Params()) -> tuple[DataFrame, int]:
    """(centroids, iterations): relevance-weighted c-means by DataFrame rounds, for sessions too large for a kernel.

    ``points`` has a column ``relevance``; each round is one grouped sum, written to the shared folder.
    """
    prm = params
    now = written(centroids.select("session_id", "roi_id", "cx", "cy"), "centroids")
    for it in range(1, prm.max_iter + 1):
        u = memberships(points, now, prm.fuzzifier).join(points.select("session_id", "poi_id", "relevance"), ["session_id", "poi_id"])
        w = F.pow("membership", F.lit(prm.fuzzifier)) * F.greatest("relevance", F.lit(1e-12))
        new = u.groupBy("session_id", "roi_id").agg((F.sum(w * F.col("mx")) / F.sum(w)).alias("nx"), (F.sum(w * F.col("my")) / F.sum(w)).alias("ny"))
        step = written(now.join(new, ["session_id", "roi_id"], "left").select("session_id", "roi_id", F.coalesce("nx", "cx").alias("cx"), F.coalesce("ny", "cy").alias("cy"), F.coalesce(F.hypot(F.col("nx") - F.col("cx"), F.col("ny") - F.col("cy")), F.lit(0.0)).alias("shift")), "centroids")
        moved = step.agg(F.max("shift")).first()[0] or 0.0
        now = step.drop("shift")
        if moved < prm.tol:
            break
    return now, it


def cohesiveness(matched: DataFrame, facets: DataFrame, n_attrs: int) -> DataFrame:
    """(session_id, roi_id, cohesiveness): mean cosine over ordered pairs of a region's points, from facet counts."""
    counts = matched.join(facets, "poi_id").groupBy("session_id", "roi_id", "attr", "val").agg(F.count("*").alias("c"))
    n = matched.groupBy("session_id", "roi_id").agg(F.count("*").alias("n"))
    s = counts.groupBy("session_id", "roi_id").agg(F.sum(F.col("c") * F.col("c")).alias("s"))
    return s.join(n, ["session_id", "roi_id"]).select("session_id", "roi_id", (F.col("s") / (F.lit(float(n_attrs)) * F.col("n") * F.col("n"))).alias("cohesiveness"))


def cohesiveness_of(counts: DataFrame, n_attrs: int) -> DataFrame:
    """``cohesiveness`` from the number of a region's points, in all and by facet (``inside.counts``)."""
    c = F.col("n").cast("double")
    s, n = F.sum(F.when(F.col("attr").isNotNull(), c * c)), F.max(F.when(F.col("attr").isNull(), c))
    got = counts.groupBy("session_id", "roi_id").agg(s.alias("s"), n.alias("n")).where("s is not null")
    return got.select("session_id", "roi_id", (F.col("s") / (F.lit(float(n_attrs)) * F.col("n") * F.col("n"))).alias("cohesiveness"))


def representativeness(rois: DataFrame) -> DataFrame:
    """(session_id, representativeness): sum of distances between the centroids of a session's regions."""
    c = rois.select("session_id", "roi_id", polygon.centroid(F.col("poly")).alias("c"))
    a = c.select("session_id", F.col("roi_id").alias("i"), F.col("c").alias("a"))
    b = c.select("session_id", F.col("roi_id").alias("j"), F.col("c").alias("b"))
    d: Column = F.hypot(F.col("a.x") - F.col("b.x"), F.col("a.y") - F.col("b.y"))
    pairs = a.join(b, "session_id").where("i < j").groupBy("session_id").agg(F.sum(d).alias("representativeness"))
    return c.select("session_id").distinct().join(pairs, "session_id", "left").fillna(0.0, ["representativeness"])
