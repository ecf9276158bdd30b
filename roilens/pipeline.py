"""The three stages together: one shot, and rounds that carry the feedback along."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .collect import segment, sources, thin
from .geo import quadtree
from .mine import intersect
from .params import Params
from .storage import written
from .suggest import facets, feedback, fuzzy, greedy, inside, match, peculiarity, relevance


@dataclass
class Shot:
    """What one round leaves behind; tables are written, so that readers do not compute them again.

    ``matched`` and ``ranked`` list every match; where they were not asked for they are plans that nothing has run.
    """

    kept: DataFrame
    segmented: DataFrame
    rois: DataFrame
    matched: DataFrame
    feedback: DataFrame
    k_primes: DataFrame
    ranked: DataFrame
    weights: DataFrame
    highlights: DataFrame


def collect(moves: DataFrame, params: Params = Params()) -> DataFrame:
    """Thinned and segmented moves."""
    return segment.segment(thin.thin(moves, params.thinning, params.eps_ms), params)


def _known(rois: DataFrame, facet_rows: DataFrame, before: DataFrame | None) -> DataFrame:
    """(session_id, attr, val, raw): what was learnt before, with an untouched cell for sessions that learnt nothing."""
    zero = rois.select("session_id").distinct().join(facets.dictionary(facet_rows).limit(1)).select("session_id", "attr", "val", F.lit(0.0).alias("raw"))
    return zero if before is None else feedback.total(zero.unionByName(before.select("session_id", "attr", "val", "raw")))


def suggest(rois: DataFrame, pois: DataFrame, params: Params = Params(), before: DataFrame | None = None, leaves: DataFrame | None = None, approach: str = "greedy", root: quadtree.Root = quadtree.Root(), learn: bool = True, listed: bool = False) -> tuple[DataFrame, ...]:
    """(matched, feedback, k_primes, ranked, weights, highlights) of regions; without ``learn`` these regions teach nothing.

    Highlights with an index need no row for each match: points are counted and ranked beside their
    regions.  ``listed`` (and the scan) takes the way through rows.
    """
    p = params
    listed = listed or leaves is None
    attrs = facets.attributes(pois)
    facet_rows = written(facets.facets(pois), "facets") if listed else facets.facets(pois)
    n_cells = facets.dictionary(facet_rows).count()
    matched = match.match(rois, pois, leaves, p.boundary, root)
    if listed:
        matched = written(matched, "matched")
        inc, met, vectors = feedback.increments(matched, facet_rows, p.delta, p.per), matched.select("session_id", "roi_id").distinct(), facets.roi_vector(matched, facet_rows)
    else:
        counts = written(inside.counts(rois, pois, attrs, p.boundary), "counts")
        inc, met, vectors = feedback.increments_of(counts, p.delta, p.per), inside.regions_met(counts), facets.vector_of(counts)
    per_roi = learn and p.update == "sequential"
    keys = ("session_id", "roi_id") if per_roi else ("session_id",)
    if not learn:
        vector = _known(rois, facet_rows, before)
    elif p.softmax == "state":
        vector = feedback.folded(inc, facets.dictionary(facet_rows))
        per_roi, keys = True, ("session_id", "roi_id")
    elif per_roi:
        vector = feedback.running(inc, met, before)
    else:
        vector = feedback.added(inc, before)
    weights = written(feedback.softmax(vector, n_cells, keys) if p.softmax == "view" else feedback.plain(vector, keys), "weights")
    scored = relevance.relevance(matched, facet_rows, weights, len(attrs), per_roi)
    if listed:
        scored = written(scored, "scored")
    pec_weights, pec_per_roi = weights, per_roi
    if p.peculiar_on == "before":
        pec_weights, pec_per_roi = feedback.softmax(_known(rois, facet_rows, before), n_cells), False
    pec = peculiarity.score(vectors, pec_weights, pec_per_roi)
    value = F.col("intent") if p.peculiarity == "intent" else F.col("printed")
    k_primes = written(pec.withColumn("peculiarity", value).withColumn("k_prime", peculiarity.k_prime(value, p.k, p.peculiarity).cast("int")), "k-primes")
    ranked = relevance.ranked(scored)
    if listed:
        ranked = written(ranked, "ranked")
    if not listed and approach == "greedy":
        found = inside.highlight(rois, pois, attrs, weights, k_primes, p, per_roi)
    elif not listed:
        found = inside.fuzzy_highlight(rois, pois, attrs, weights, k_primes, p, per_roi)
    elif approach == "greedy":
        found = greedy.highlight(ranked, pois, k_primes, attrs, p)
    else:
        found = fuzzy.highlight(rois, matched, scored, pois, k_primes, attrs, p)
    raw = feedback.added(inc, before) if learn else _known(rois, facet_rows, before)
    return matched, written(raw, "feedback"), k_primes, ranked, weights, written(found, "highlights")


def shot(moves: DataFrame, pois: DataFrame, params: Params = Params(), before: DataFrame | None = None, approach: str = "greedy", learn: bool = True, relearn: bool = False, listed: bool = False) -> Shot:
    """One pass of collecting, mining and suggesting.

    Without ``learn`` the feedback stays what it was before.  With ``relearn`` the moves hold all that
    ``before`` was learnt from: it only stretches regions, and the feedback starts anew.  With ``listed``
    every match is written as a row, for readers of ``matched`` and ``ranked``.
    """
    p = params
    root = quadtree.Root.around(pois)
    leaves = quadtree.build(pois, p.capacity, p.max_depth + root.bits - quadtree.Root.bits, root) if p.use_index or p.g == "auto" else None
    if leaves is not None and (listed or p.g == "auto"):
        leaves = written(leaves, "leaves")
    if p.g == "auto":
        p = p.but(g=segment.g_from_leaves(leaves))
    kept = written(thin.thin(moves, p.thinning, p.eps_ms), "kept")
    segmented = written(segment.segment(kept, p), "segmented")
    rois = written(intersect.discover(segmented, p, before), "rois")
    matched, raw, k_primes, ranked, weights, found = suggest(rois, pois, p, None if relearn else before, leaves if p.use_index else None, approach, root, learn, listed)
    return Shot(kept, segmented, rois, matched, raw, k_primes, ranked, weights, found)


def single_shot(spark: SparkSession, sf_dir: str, params: Params = Params(), approach: str = "greedy", poi_carrier: str = "part") -> DataFrame:
    """Highlights of carriers M and P (or another POI carrier)."""
    return shot(sources.moves(spark, sf_dir), facets.carrier(spark, sf_dir, poi_carrier), params, None, approach).highlights


def iterate(spark: SparkSession, moves_by_round: list[DataFrame], pois: DataFrame, params: Params = Params(), freeze_after: int | None = None, approach: str = "greedy") -> tuple[DataFrame, list[Shot]]:
    """(highlights of all rounds with ``round``, the shots): feedback and the round number carry over.

    All sessions go through a round together.  ``freeze_after`` stops learning after that round,
    inside rounds too.
    """
    before, shots, out = None, [], None
    for i, moves in enumerate(moves_by_round, 1):
        learns = freeze_after is None or i <= freeze_after
        s = shot(moves, pois, params.but(rounds_done=i), before, approach, learns)
        if learns:
            # sessions without matches in this round keep what they had
            before = s.feedback if before is None else written(before.join(s.feedback.select("session_id", "attr", "val"), ["session_id", "attr", "val"], "left_anti").unionByName(s.feedback), "carried")
        shots.append(s)
        found = s.highlights.withColumn("round", F.lit(i))
        out = found if out is None else out.unionByName(found)
    return out, shots
