"""Regions with the points inside them, without a row for each pair.

A region goes with all points near it to one kernel, which finds the points inside by the exact test
on distinct pixels and hands on what is asked of them: counts by facet, the first few in some order, or
a lazy ranking.  Only those results become rows, so tables grow with the regions and not with matches.

A region is dealt to the tile of its lower left corner, of a side no less than its box, and a point to
the tile it lies in and the three to its left and below.  Tiles with many regions are split by region.
What is asked of a session's regions together (fuzzy highlights) deals them by the box of all of them.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..geo import polygon
from ..params import Params
from ..storage import stored, written
from . import fuzzy
from .greedy import SCHEMA, swap_scan

SIDE = 128  # of the smallest tiles, in pixels; others are larger by powers of four
REGIONS = 4096  # of a tile that one kernel call takes, about


def _ranges(low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """All whole numbers of [low, high), one range after another."""
    n = np.maximum(high - low, 0)
    return np.repeat(low - np.cumsum(n) + n, n) + np.arange(n.sum())


class Points:
    """A tile's points by pixel, with their attributes' values numbered over all attributes (0: none)."""

    def __init__(self, table: pa.Table, attrs: Sequence[str]):
        mx, my = table["mx"].to_numpy(), table["my"].to_numpy()
        order = np.lexsort([mx, my])
        mx, my = mx[order], my[order]
        self.x0, self.y0, self.x1, self.y1 = (int(v) for v in (mx.min(), my.min(), mx.max(), my.max()))
        self.width = self.x1 - self.x0 + 1
        key = (my - self.y0) * self.width + (mx - self.x0)
        self.pixel, first = np.unique(key, return_index=True)
        self.first = np.append(first, len(key))
        self.px, self.py = mx[first].astype(float), my[first].astype(float)
        self.ids = table["poi_id"].to_numpy()[order]
        self.order = order
        self.names: list[tuple[str | None, str | None]] = [(None, None)]
        codes = []
        for a in attrs:
            d = table[a].combine_chunks().dictionary_encode()
            codes.append(d.indices.fill_null(-1).to_numpy(zero_copy_only=False)[order].astype(np.int64))
            codes[-1] = np.where(codes[-1] < 0, 0, codes[-1] + len(self.names))
            self.names += [(a, v) for v in d.dictionary.to_pylist()]
        self.codes = np.column_stack(codes) if codes else np.zeros((len(order), 0), np.int64)

    def inside(self, corners: np.ndarray, boundary: bool = False) -> np.ndarray:
        """Positions of the points that ``polygon.contains`` of these corners, by the same arithmetic."""
        if len(corners) < 3:
            return np.empty(0, np.int64)
        left, right = max(np.ceil(corners[:, 0].min()), self.x0), min(np.floor(corners[:, 0].max()), self.x1)
        rows = np.arange(max(np.ceil(corners[:, 1].min()), self.y0), min(np.floor(corners[:, 1].max()), self.y1) + 1).astype(np.int64)
        if left > right or not len(rows):
            return np.empty(0, np.int64)
        start = (rows - self.y0) * self.width - self.x0
        at = _ranges(np.searchsorted(self.pixel, start + int(left)), np.searchsorted(self.pixel, start + int(right), "right"))
        x, y = self.px[at], self.py[at]
        ok = np.ones(len(at), bool)
        for (ax, ay), (bx, by) in zip(corners.tolist(), np.roll(corners, -1, 0).tolist(), strict=True):
            dx, dy = bx - ax, by - ay
            if dx or dy:
                c = dx * (y - ay) - dy * (x - ax)
                near = polygon.ON_EDGE * np.hypot(dx, dy)
                ok &= c >= -near if boundary else c > near
        at = at[ok]
        return _ranges(self.first[at], self.first[at + 1])


def _corners(table: pa.Table) -> Iterator[np.ndarray]:
    """The corners of each row's polygon."""
    polys = table["poly"].combine_chunks()
    flat = polys.flatten()
    xy = np.column_stack([flat.field("x").to_numpy(zero_copy_only=False), flat.field("y").to_numpy(zero_copy_only=False)])
    upto = np.cumsum(polys.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))
    return iter(np.split(xy, upto[:-1]))


def meet(regions: DataFrame, pois: DataFrame, attrs: Sequence[str], work: Callable[[Points, pa.Table], list[tuple]], schema: str, kinds: Sequence[pa.DataType], together: bool = False) -> DataFrame:
    """``work``'s rows over every tile: regions have session_id, roi_id, poly and more, pois poi_id, mx, my, ``attrs`` and more.

    With ``together`` all regions of a session come to the same call.
    """
    b, w = polygon.bbox(F.col("poly")), W.partitionBy("session_id")
    span = F.greatest(F.col("_b.x1") - F.col("_b.x0"), F.col("_b.y1") - F.col("_b.y0"), F.lit(1.0))
    side = F.lit(float(SIDE)) * F.pow(F.lit(4.0), F.greatest(F.ceil(F.log(4.0, span * 1.0001 / SIDE)), F.lit(0)))
    tile = ["_side", "_gx", "_gy"]
    dealt = regions.where("size(poly) >= 3").withColumn("_b", b)
    if together:
        dealt = dealt.withColumn("_b", F.struct(*(least(f"_b.{c}").over(w).alias(c) for c, least in (("x0", F.min), ("y0", F.min), ("x1", F.max), ("y1", F.max)))))
    dealt = dealt.withColumn("_side", side.cast("long"))
    dealt = dealt.withColumn("_gx", F.floor(F.col("_b.x0") / F.col("_side"))).withColumn("_gy", F.floor(F.col("_b.y0") / F.col("_side"))).drop("_b")
    dealt = stored(dealt.withColumn("_h", F.xxhash64("session_id", *[] if together else ["roi_id"])), "dealt")
    tiles = written(dealt.groupBy(*tile).agg(F.ceil(F.count("*") / F.lit(float(REGIONS))).alias("_of")), "tiles")
    dealt = dealt.join(tiles, tile).withColumn("_slot", F.pmod("_h", "_of")).drop("_of", "_h")
    p = pois.where("mx is not null and my is not null").crossJoin(F.broadcast(tiles.select("_side").distinct()))  # as many rows as powers of four
    for axis in "xy":
        at = F.floor(F.col(f"m{axis}") / F.col("_side"))
        p = p.withColumn(f"_g{axis}", F.explode(F.array(at, at - 1)))
    p = p.join(tiles, tile)
    if together:  # few wide tiles with many slots: the rows to deal are spread over tasks first
        p = p.repartition(int(p.sparkSession.conf.get("spark.sql.shuffle.partitions")), "poi_id")
    p = p.withColumn("_slot", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_of") - 1))).drop("_of")
    names = [part.split()[0] for part in schema.split(", ")]

    def kernel(regs: pa.Table, points: pa.Table) -> pa.Table:
        rows = work(Points(points, attrs), regs) if regs.num_rows and points.num_rows else []
        cols = list(zip(*rows, strict=True)) or [()] * len(names)
        return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

    keys = [*tile, "_slot"]
    return dealt.groupBy(*keys).cogroup(p.groupBy(*keys)).applyInArrow(kernel, schema)


def counts(rois: DataFrame, pois: DataFrame, attrs: Sequence[str], boundary: bool = False) -> DataFrame:
    """(session_id, roi_id, attr, val, n): points inside each region by facet; a row without attr counts all of them."""

    def work(points: Points, regs: pa.Table) -> list[tuple]:
        out = []
        for session, roi, corners in zip(regs["session_id"].to_pylist(), regs["roi_id"].to_pylist(), _corners(regs), strict=True):
            at = points.inside(corners, boundary)
            if len(at):
                n = np.bincount(points.codes[at].ravel(), minlength=len(points.names))
                n[0] = len(at)
                some = np.flatnonzero(n)
                out += [(session, roi, *points.names[i], c) for i, c in zip(some.tolist(), n[some].tolist(), strict=True)]
        return out

    kinds = (pa.int64(), pa.int32(), pa.string(), pa.string(), pa.int64())
    regions = rois.select("session_id", F.col("roi_id").cast("int").alias("roi_id"), "poly")
    return meet(regions, pois.select("poi_id", "mx", "my", *attrs), attrs, work, "session_id long, roi_id int, attr string, val string, n long", kinds)


def regions_met(counts: DataFrame) -> DataFrame:
    """(session_id, roi_id) of regions with points, from ``counts``."""
    return counts.where("attr is null").select("session_id", "roi_id")


def first_k(rois: DataFrame, pois: DataFrame, order: str, k: int, boundary: bool = False) -> DataFrame:
    """(session_id, roi_id, poi_id, rank): the k points inside each region that come first by the expression ``order``, ties by poi_id."""

    def work(points: Points, regs: pa.Table, by: np.ndarray) -> list[tuple]:
        place = np.empty(len(points.ids), np.int64)
        sequence = np.lexsort([points.ids, by[points.order]])
        place[sequence] = np.arange(len(sequence))
        out = []
        for session, roi, corners in zip(regs["session_id"].to_pylist(), regs["roi_id"].to_pylist(), _corners(regs), strict=True):
            found = place[points.inside(corners, boundary)]
            if len(found) > k:
                found = np.partition(found, k)[:k]
            out += [(session, roi, p, n) for n, p in enumerate(points.ids[sequence[np.sort(found)]].tolist(), 1)]
        return out

    return _with_order(rois, pois, order, work)


def _with_order(rois: DataFrame, pois: DataFrame, order: str, work) -> DataFrame:
    kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int32())
    regions = rois.select("session_id", F.col("roi_id").cast("int").alias("roi_id"), "poly")
    at = pois.select("poi_id", "mx", "my", F.expr(order).cast("long").alias("_order"))
    return meet(regions, at, ("_order",), lambda points, regs: work(points, regs, _numbers(points)), "session_id long, roi_id int, poi_id long, rank int", kinds)


def _numbers(points: Points) -> np.ndarray:
    """The values of a single numeric attribute, in the order of the table that the points came in."""
    values = np.array([0, *(v for _, v in points.names[1:])], np.int64)
    out = np.empty(len(points.ids), np.int64)
    out[points.order] = values[points.codes[:, 0]]
    return out


class Ranking(Sequence):
    """Attribute tuples of points in order of falling relevance, ties by id, sorted as far as they are read."""

    def __init__(self, points: Points, at: np.ndarray, relevance: np.ndarray, most: int | None = None):
        self.points, self.at, self.relevance = points, at, relevance
        self.rounded = np.round(relevance, 9)
        self.size = len(at) if most is None else min(len(at), most)
        self.sorted = np.empty(0, np.int64)

    def __len__(self) -> int:
        return self.size

    def places(self, n: int) -> np.ndarray:
        """At least the first n places of the order (all there are, if fewer)."""
        if len(self.sorted) < min(n, len(self.at)):
            n = min(len(self.at), max(64, 4 * n))
            least = np.partition(self.rounded, len(self.at) - n)[len(self.at) - n]
            some = np.flatnonzero(self.rounded >= least)
            self.sorted = some[np.lexsort([self.points.ids[self.at[some]], -self.rounded[some]])]
        return self.sorted

    def __getitem__(self, i: int) -> tuple:
        if i >= self.size:
            raise IndexError(i)
        return tuple(c or None for c in self.points.codes[self.at[self.places(i + 1)[i]]].tolist())


def _rankings(points: Points, regs: pa.Table, n_attrs: int, boundary: bool, most: Callable[[int], int | None]) -> Iterator[tuple[int, int, int, Ranking]]:
    """(session_id, roi_id, k_prime, ranking) of a tile's regions."""
    for _, session, roi, k, at, rel in _scored(points, regs, n_attrs, boundary):
        yield session, roi, k, Ranking(points, at, rel, most(k))


def _scored(points: Points, regs: pa.Table, n_attrs: int, boundary: bool) -> Iterator[tuple[int, int, int, int, np.ndarray, np.ndarray]]:
    """(row, session_id, roi_id, k_prime, points inside, their relevance) of a tile's regions, scored as ``relevance`` does."""
    number = {name: i for i, name in enumerate(points.names)}
    weights = regs["weights"].combine_chunks()
    flat = weights.flatten()
    which = np.array([number.get(x, -1) for x in zip(flat.field("attr").to_pylist(), flat.field("val").to_pylist(), strict=True)], np.int64)
    value = flat.field("weight").to_numpy(zero_copy_only=False)
    upto = np.cumsum([0, *weights.value_lengths().to_pylist()]).tolist()
    known = (points.codes > 0).any(1)
    columns = (regs[c].to_pylist() for c in ("session_id", "roi_id", "k_prime", "norm", "w0"))
    for i, (session, roi, k, norm, w0, corners) in enumerate(zip(*columns, _corners(regs), strict=True)):
        at = points.inside(corners, boundary)
        at = at[known[at]]
        if not len(at):
            continue
        w = np.full(len(points.names), w0)
        some = which[upto[i] : upto[i + 1]]
        w[some[some >= 0]] = value[upto[i] : upto[i + 1]][some >= 0]
        w[0] = 0.0
        by = norm * float(n_attrs) ** 0.5
        dot = w[points.codes[at]].sum(1)
        yield i, session, roi, k, at, dot / by if by else np.zeros(len(at))


def _weighted(rois: DataFrame, weights: DataFrame, k_primes: DataFrame, per_roi: bool, least: int = 1) -> DataFrame:
    """Regions with k_prime of at least ``least`` and the weights that score their points."""
    keys = ["session_id", "roi_id"] if per_roi else ["session_id"]
    w = weights.groupBy(*keys).agg(F.collect_list(F.struct("attr", "val", "weight")).alias("weights"), F.max("norm").alias("norm"), F.max("w0").alias("w0"))
    k = k_primes.where(F.col("k_prime") >= least).select("session_id", "roi_id", F.col("k_prime").cast("int").alias("k_prime"))
    regions = rois.select("session_id", "roi_id", "poly").join(k, ["session_id", "roi_id"]).join(w, keys)
    return regions.withColumn("roi_id", F.col("roi_id").cast("int"))


def best(rois: DataFrame, pois: DataFrame, attrs: Sequence[str], weights: DataFrame, k_primes: DataFrame, per_roi: bool = True, boundary: bool = False) -> DataFrame:
    """(session_id, roi_id, rank, poi_id, relevance): the k' most relevant points of each region."""

    def work(points: Points, regs: pa.Table) -> list[tuple]:
        out = []
        for session, roi, k, r in _rankings(points, regs, len(attrs), boundary, lambda k: None):
            for n, i in enumerate(r.places(k)[:k].tolist(), 1):
                out.append((session, roi, n, int(points.ids[r.at[i]]), float(r.relevance[i])))
        return out

    kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64())
    return meet(_weighted(rois, weights, k_primes, per_roi), pois.select("poi_id", "mx", "my", *attrs), attrs, work, "session_id long, roi_id int, rank int, poi_id long, relevance double", kinds)


def highlight(rois: DataFrame, pois: DataFrame, attrs: Sequence[str], weights: DataFrame, k_primes: DataFrame, params: Params = Params(), per_roi: bool = True) -> DataFrame:
    """``greedy.highlight`` of every region; the scan reads as much of the ranking as it gets to."""
    p = params

    def most(k: int) -> int | None:
        return None if p.max_scan is None else min(k, p.k) + p.max_scan

    def work(points: Points, regs: pa.Table) -> list[tuple]:
        out = []
        for session, roi, k, r in _rankings(points, regs, len(attrs), p.boundary, most):
            chosen, scanned, why = swap_scan(r, k, p.threshold, p.guard, p.swap, p.diversity, p.max_scan, p.time_limit_ms)
            for n, c in enumerate(sorted(chosen), 1):
                i = int(r.places(c + 1)[c])
                out.append((session, roi, n, int(points.ids[r.at[i]]), float(r.relevance[i]), k, scanned, why))
        return out

    kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int32(), pa.int32(), pa.string())
    return meet(_weighted(rois, weights, k_primes, per_roi), pois.select("poi_id", "mx", "my", *attrs), attrs, work, SCHEMA, kinds)


def _together(points: Points, regs: pa.Table, n_attrs: int, boundary: bool) -> Iterator[tuple[int, list[tuple]]]:
    """(session_id, its regions as (row, roi_id, k_prime, points inside, relevance)), regions in order of roi_id."""
    group, now = [], None
    for i, session, *rest in _scored(points, regs, n_attrs, boundary):
        if group and session != now:
            yield now, group
            group = []
        now = session
        group.append((i, *rest))
    if group:
        yield now, group


def fuzzy_highlight(rois: DataFrame, pois: DataFrame, attrs: Sequence[str], weights: DataFrame, k_primes: DataFrame, params: Params = Params(), per_roi: bool = True) -> DataFrame:
    """``fuzzy.highlight`` of every session, whose regions come to the kernel together and beside the points."""
    p = params
    centre = polygon.centroid(F.col("poly"))
    regions = _weighted(rois, weights, k_primes, per_roi, 0).withColumn("cx", centre["x"]).withColumn("cy", centre["y"])

    def work(points: Points, regs: pa.Table) -> list[tuple]:
        out = []
        regs = regs.take(pc.sort_indices(regs.select(["session_id", "roi_id"]), [("session_id", "ascending"), ("roi_id", "ascending")]))
        cx, cy = regs["cx"].to_numpy(), regs["cy"].to_numpy()
        pixel = np.repeat(np.arange(len(points.pixel)), np.diff(points.first))
        for session, group in _together(points, regs, len(attrs), p.boundary):
            rows, ids, k, at, rel = zip(*group, strict=True)
            inside = np.zeros(len(pixel), bool)
            for a in at:
                inside[a] = True
            some = np.flatnonzero(inside)
            place = np.empty(len(pixel), np.int64)
            place[some] = np.arange(len(some))
            crowd = fuzzy.Crowd(points.ids[some], points.px[pixel[some]], points.py[pixel[some]], points.codes[some], len(points.names), [place[a] for a in at], rel)
            c = np.column_stack([cx[list(rows)], cy[list(rows)]])
            chosen, it, shift, last = crowd.highlights(c, np.array(k), p)
            for roi, kp, best in zip(ids, k, chosen, strict=True):
                out += [(session, roi, n, *b, kp, it, shift, last) for n, b in enumerate(best, 1)]
        return out

    return meet(regions, pois.select("poi_id", "mx", "my", *attrs), attrs, work, fuzzy.SCHEMA, fuzzy.KINDS, True)
