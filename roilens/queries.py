"""Named queries over the given tables: methods, variants, baselines, measures and workloads.

Each takes (spark, sf_dir) and returns a flat DataFrame; numbers from floating sums are rounded to six
decimals, so that another engine's order of addition gives the same rows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import pipeline
from .collect import features, fuse, segment, sources, thin
from .eval import baselines, measures, workloads
from .geo import polygon, projection, quadtree
from .mine import cluster, hull, intersect, personalize
from .params import PROFILE_EPS, Params
from .relational.ops import OPS
from .storage import written
from .streaming import ops as _streaming_ops  # noqa: F401  (registers its entries)
from .suggest import facets, feedback, fuzzy, inside, match, peculiarity, relevance, sequence

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
TIGHT = Params(stretch="none")


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


def _six(*names: str):
    return [F.round(n, 6).alias(n) for n in names]


# ---- collecting


@query
def q_project_roundtrip(s, d):
    m = sources.moves(s, d).select("event_id", "x", "y")
    lat, lon = projection.to_map(F.col("x").cast("double"), F.col("y").cast("double"))
    m = m.withColumn("lat", lat).withColumn("lon", lon)
    bx, by = projection.to_screen(F.col("lat"), F.col("lon"))
    return m.select("event_id", *_six("lat", "lon"), F.round(bx, 3).alias("bx"), F.round(by, 3).alias("by"))


@query
def q_recentre(s, d):
    """As-of viewport of every move: the centre shifts every ten seconds of session time."""
    m = sources.moves(s, d).select("session_id", "event_id", "t_ms", "x", "y")
    v = m.select("session_id").distinct().withColumn("i", F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))))
    v = v.select("session_id", (F.col("i") * 10_000).cast("long").alias("t_ms"), (F.lit(48.0) + F.col("i") * 0.5).alias("gamma"), (F.lit(2.0) + F.col("i")).alias("theta"), F.lit(10000.0).alias("ppd"))
    return projection.with_viewport(m, v).select("event_id", *_six("lat", "lon"))


@query
def q_thin_grid(s, d):
    return thin.grid(sources.moves(s, d)).select("session_id", "event_id", "t_ms", "x", "y")


@query
def q_thin_refractory(s, d):
    return thin.refractory(sources.moves(s, d)).select("session_id", "event_id", "t_ms")


@query
def q_drop_repeats(s, d):
    return thin.drop_repeats(sources.moves(s, d, "still")).select("session_id", "event_id")


@query
def q_kinematics(s, d):
    return features.kinematics(thin.grid(sources.moves(s, d))).select("session_id", "event_id", "dt_ms", *_six("dist", "speed"), "dwell_ms")


@query
def q_dwell(s, d):
    return features.dwell_by(sources.moves(s, d), "session_id", "true_spot")


def _kept(s, d, kind: str = "hover") -> DataFrame:
    return thin.grid(sources.moves(s, d, kind))


@query
def q_seg_fixed(s, d):
    return segment.summary(segment.segment(_kept(s, d)))


@query
def q_seg_fixed_length(s, d):
    return segment.summary(segment.segment(_kept(s, d), Params(g=None, length_ms=7000)))


@query
def q_seg_auto(s, d):
    """As many segments as the density of points on the map suggests."""
    return segment.summary(segment.segment(_kept(s, d), Params(g=segment.g_from_leaves(quadtree.build(facets.carrier(s, d))))))


@query
def q_seg_closed_only(s, d):
    return segment.summary(segment.segment(_kept(s, d), Params(keep_open=False)))


@query
def q_seg_idle_gap(s, d):
    return segment.summary(segment.segment(_kept(s, d), Params(strategy="idle", evidence="gap")))


@query
def q_seg_idle_still(s, d):
    return segment.summary(segment.segment(_kept(s, d, "still"), Params(strategy="idle", evidence="still")))


@query
def q_seg_idle_either(s, d):
    return segment.summary(segment.segment(_kept(s, d), Params(strategy="idle", evidence="either")))


@query
def q_seg_drift_tiered(s, d):
    return segment.summary(segment.segment(_kept(s, d, "drift"), Params(strategy="drift")))


@query
def q_seg_drift_interp(s, d):
    return segment.summary(segment.segment(_kept(s, d, "drift"), Params(strategy="drift", detector="interp")))


@query
def q_seg_drift_cusum(s, d):
    return segment.summary(segment.segment(_kept(s, d, "drift"), Params(strategy="drift", detector="cusum")))


@query
def q_signal_fusion(s, d):
    return fuse.fuse({"hover": (sources.moves(s, d), 1.0), "voice": (sources.voice(s, d), 3.0)}).groupBy("signal").agg(F.count("*").alias("n"), F.sum("weight").alias("weight"))


@query
def q_signal_kinds(s, d):
    """Every kind of signal as moves, by its registered mapping; the kinds' columns are made from pointer moves."""
    raw = sources.moves(s, d).select(
        "session_id", "event_id", "t_ms", "x", "y", F.col("x").alias("gaze_x"), (F.col("y") + 1).alias("gaze_y"), (F.col("t_ms") % 50).alias("delta_y"), (F.col("x") - 3).alias("x1"), (F.col("x") + 3).alias("x2"),
        (F.col("y") - 5).alias("y1"), (F.col("y") + 5).alias("y2"), F.col("x").alias("centre_x"), F.col("y").alias("centre_y"), (F.col("x") + 2).alias("item_x"), (F.col("y") - 2).alias("item_y"),
    )
    out = None
    for kind in sorted(sources.SIGNALS):
        m = sources.from_signal(raw, kind)
        out = m if out is None else out.unionByName(m)
    return out.groupBy("signal").agg(F.count("*").alias("n"), F.sum("x").alias("sx"), F.sum("y").alias("sy"))


@query
def q_eps_profile(s, d):
    """Moves kept at the sampling gap of each user's profile."""
    m = sources.moves(s, d)
    out = None
    for profile in PROFILE_EPS:
        kept = thin.grid(m, Params.eps_for(profile)).agg(F.count("*").alias("kept")).select(F.lit(profile).alias("profile"), "kept")
        out = kept if out is None else out.unionByName(kept)
    return out


@query
def q_density_surface(s, d):
    return cluster.density_surface(_kept(s, d))


# ---- mining


def _segmented(s, d) -> DataFrame:
    return segment.segment(_kept(s, d))


def _clustered(s, d, params: Params = TIGHT) -> DataFrame:
    return cluster.dbscan(_segmented(s, d), params)


def _hulls(s, d) -> DataFrame:
    return hull.convex_hull(_clustered(s, d))


def _rois(s, d, params: Params = TIGHT) -> DataFrame:
    return intersect.discover(_segmented(s, d), params)


@query
def q_dbscan_roles(s, d):
    return cluster.roles(_clustered(s, d))


@query
def q_dbscan_clusters(s, d):
    return _clustered(s, d).select("session_id", "seg", "event_id", "cluster_id", "role")


@query
def q_dbscan_distributed(s, d):
    return cluster.distributed(_segmented(s, d), TIGHT).select("session_id", "seg", "event_id", "cluster_id", "role")


@query
def q_dbscan_temporal(s, d):
    return _clustered(s, d, TIGHT.but(eps_t=2000)).select("session_id", "seg", "event_id", "cluster_id", "role")


@query
def q_dbscan_mean_deviation(s, d):
    return _clustered(s, d, TIGHT.but(delta_mean=25.0)).select("session_id", "seg", "event_id", "cluster_id", "role")


@query
def q_reachable(s, d):
    return cluster.reachable(_segmented(s, d))


@query
def q_reachable_chains(s, d):
    return cluster.linked(_segmented(s, d), TIGHT)


@query
def q_hull_prune(s, d):
    return hull.prune(_clustered(s, d), 4).groupBy("session_id", "seg", "cluster_id").agg(F.count("*").alias("left"))


@query
def q_hull_vertices(s, d):
    return _hulls(s, d).select("session_id", "seg", "cluster_id", F.inline("poly")).select("session_id", F.col("seg").cast("int").alias("seg"), "cluster_id", "x", "y")


@query
def q_hull_area(s, d):
    return _hulls(s, d).select("session_id", "cluster_id", F.round("area", 6).alias("area"), F.round(polygon.perimeter(F.col("poly")), 6).alias("perimeter"))


@query
def q_hull_angular(s, d):
    return hull.convex_hull(_clustered(s, d), "angular", 0).select("session_id", "cluster_id", F.round("area", 6).alias("area"))


@query
def q_confidence(s, d):
    return workloads.confidence_curve(s, d)


def _stretched(s, d, mode: str) -> DataFrame:
    polys = _hulls(s, d).withColumn("confidence", (F.col("session_id") % 5) / F.lit(4.0))
    out = personalize.stretch(polys, mode).where("area0 > 0")
    return out.select("session_id", "cluster_id", F.round(polygon.area(F.col("poly")), 4).alias("area"))


@query
def q_stretch_area_printed(s, d):
    return _stretched(s, d, "printed")


@query
def q_stretch_area_intent(s, d):
    return _stretched(s, d, "intent")


@query
def q_stretch_report(s, d):
    polys = _hulls(s, d).withColumn("confidence", (F.col("session_id") % 5) / F.lit(4.0))
    return measures.stretch_report(personalize.stretch(polys)).select("session_id", *_six("confidence", "ratio"))


@query
def q_roi_pairs(s, d):
    return _rois(s, d).select("session_id", "roi_id", F.col("src")[0].alias("src_a"), F.col("src")[1].alias("src_b"))


@query
def q_roi_area(s, d):
    return _rois(s, d).select("session_id", "roi_id", F.round("area", 4).alias("area"))


@query
def q_roi_cross_segment(s, d):
    return _rois(s, d, TIGHT.but(pairs="cross_segment")).select("session_id", F.col("src")[0].alias("src_a"), F.col("src")[1].alias("src_b"))


@query
def q_roi_support3(s, d):
    return _rois(s, d, TIGHT.but(min_support=3)).select("session_id", "roi_id", F.array_join(F.transform("src", lambda x: x.cast("string")), ",").alias("src"), F.round("area", 4).alias("area"))


@query
def q_roi_merged(s, d):
    return intersect.merge_rois(_rois(s, d))


@query
def q_roi_printed_stretch(s, d):
    return _rois(s, d, Params()).select("session_id", "roi_id", F.round("area", 4).alias("area"))


@query
def q_roi_geojson(s, d):
    return _rois(s, d).select("session_id", "roi_id", polygon.geojson(F.col("poly")).alias("geojson"))


@query
def q_mine_report(s, d):
    return measures.mine_report(_clustered(s, d)).select("session_id", "segments", "clusters", *_six("noise_share"))


@query
def q_region_recovery(s, d):
    c = written(_clustered(s, d), "clustered")
    return measures.region_recovery(c, _rois(s, d), list(zip(sources.ANCHOR_X, sources.ANCHOR_Y, strict=True))).select("session_id", *_six("purity"), "spots_found")


# ---- index and matching


@query
def q_quadtree_leaves(s, d):
    return quadtree.build(facets.carrier(s, d)).select("depth", "code", "n")


@query
def q_quadtree_cover(s, d):
    return quadtree.cover(_rois(s, d), quadtree.build(facets.carrier(s, d))).select("session_id", "roi_id", "depth", "code")


@query
def q_match(s, d):
    p = facets.carrier(s, d)
    return match.match(_rois(s, d), p, quadtree.build(p))


@query
def q_match_scan(s, d):
    return match.match(_rois(s, d), facets.carrier(s, d))


@query
def q_out_of_sight(s, d):
    p = facets.carrier(s, d)
    return match.out_of_sight(match.match(_rois(s, d), p, quadtree.build(p)), p, _kept(s, d), 20)


@query
def q_index_selectivity(s, d):
    p = facets.carrier(s, d)
    lv = written(quadtree.build(p), "leaves")
    r = written(_rois(s, d), "rois")
    return measures.selectivity(match.candidates(r, p, lv), p.count(), r.count()).select("candidates", "exact_tests", *_six("of_scan", "of_candidates"))


# ---- feedback and relevance


def _matched(s, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    p = facets.carrier(s, d)
    return written(match.match(_rois(s, d), p, quadtree.build(p)), "matched"), p, written(facets.facets(p), "facets")


def _regions(s, d) -> tuple[DataFrame, DataFrame]:
    return written(_rois(s, d), "rois"), facets.carrier(s, d)


def _counts(s, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Points of regions by facet, and what they come from: a region's matches are counted, not listed."""
    r, p = _regions(s, d)
    return inside.counts(r, p, facets.attributes(p)), r, p


def _increments(s, d, per: str = "point") -> DataFrame:
    return feedback.increments_of(_counts(s, d)[0], per=per)


@query
def q_roi_vector(s, d):
    return facets.vector_of(_counts(s, d)[0])


@query
def q_feedback_batch(s, d):
    return feedback.added(_increments(s, d)).select("session_id", "attr", "val", *_six("raw"))


@query
def q_feedback_per_value(s, d):
    return feedback.added(_increments(s, d, "value")).select("session_id", "attr", "val", *_six("raw"))


@query
def q_feedback_sequential(s, d):
    c = written(_counts(s, d)[0], "counts")
    return feedback.running(feedback.increments_of(c), inside.regions_met(c)).where("raw > 0").select("session_id", "roi_id", "attr", "val", *_six("raw"))


@query
def q_feedback_state(s, d):
    c, _, p = _counts(s, d)
    return feedback.folded(feedback.increments_of(c), facets.dictionary(facets.facets(p))).select("session_id", "roi_id", "attr", "val", *_six("raw"))


def _weights(s, d) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(points of regions by facet, regions, POIs, weights of sessions)."""
    c, r, p = _counts(s, d)
    c = written(c, "counts")
    return c, r, p, feedback.softmax(feedback.added(feedback.increments_of(c)), facets.dictionary(facets.facets(p)).count())


@query
def q_softmax(s, d):
    return _weights(s, d)[3].select("session_id", "attr", "val", *_six("weight", "w0", "norm"))


@query
def q_feedback_explain(s, d):
    return feedback.explain(feedback.added(_increments(s, d)).select("session_id", "attr", "val", *_six("raw")))


@query
def q_feedback_clicks(s, d):
    c, _, p = _counts(s, d)
    raw = written(feedback.added(feedback.increments_of(c)), "feedback")
    c = sources.clicks(s, d).join(raw.select("session_id").distinct(), "session_id", "left_semi")
    return feedback.with_clicks(raw, c, facets.facets(p), 0.1).select("session_id", "attr", "val", *_six("raw"))


@query
def q_feedback_decay(s, d):
    inc = _increments(s, d).withColumn("round", F.col("roi_id"))
    return feedback.decayed(inc, 30, 0.1).select("session_id", "attr", "val", *_six("raw"))


@query
def q_relevance(s, d):
    _, r, p, w = _weights(s, d)
    m, f = match.match(r, p, quadtree.build(p)), facets.facets(p)
    return relevance.relevance(m, f, w, len(facets.attributes(p)), False).select("session_id", "roi_id", "poi_id", *_six("relevance"))


@query
def q_peculiarity_printed(s, d):
    c, _, _, w = _weights(s, d)
    return peculiarity.score(facets.vector_of(c), w, False).select("session_id", "roi_id", *_six("printed"))


@query
def q_peculiarity_intent(s, d):
    c, _, _, w = _weights(s, d)
    return peculiarity.score(facets.vector_of(c), w, False).select("session_id", "roi_id", *_six("intent"))


@query
def q_roi_alignment(s, d):
    c, _, _, w = _weights(s, d)
    return measures.roi_alignment(facets.vector_of(c), w, False).select("session_id", "roi_id", *_six("alignment"))


@query
def q_kprime(s, d):
    c, _, _, w = _weights(s, d)
    p = peculiarity.score(facets.vector_of(c), w, False)
    return p.select("session_id", "roi_id", peculiarity.k_prime(F.col("printed"), 5).alias("k_prime"))


@query
def q_greedy_seed(s, d):
    c, r, p, w = _weights(s, d)
    k = peculiarity.score(facets.vector_of(c), w, False).select("session_id", "roi_id", peculiarity.k_prime(F.col("printed"), 5).alias("k_prime"))
    return inside.best(r, p, facets.attributes(p), w, k, False).select("session_id", "roi_id", "rank", "poi_id")


# ---- highlights, measures, baselines


def _shot(s, d, params: Params = Params(), approach: str = "greedy") -> pipeline.Shot:
    return pipeline.shot(sources.moves(s, d), facets.carrier(s, d), params, None, approach)


def _rounded(h: DataFrame) -> DataFrame:
    return h.select("session_id", "roi_id", "rank", "poi_id", *_six("relevance"))


@query
def q_greedy_intent(s, d):
    return _rounded(_shot(s, d).highlights)


@query
def q_greedy_printed(s, d):
    return _rounded(_shot(s, d, Params(guard="printed")).highlights)


@query
def q_greedy_best(s, d):
    return _rounded(_shot(s, d, Params(swap="best")).highlights)


@query
def q_fuzzy_topk(s, d):
    return _rounded(_shot(s, d, Params(), "fuzzy").highlights)


@query
def q_fuzzy_cmeans(s, d):
    return _rounded(_shot(s, d, Params(fuzzy="cmeans"), "fuzzy").highlights)


@query
def q_fuzzy_rest(s, d):
    """How many rounds the centroids took to rest, their last shift and the last objective."""
    h = _shot(s, d, Params(), "fuzzy").highlights
    return h.select("session_id", "iterations", *_six("shift", "objective")).distinct()


@query
def q_greedy_stops(s, d):
    """How many points the swap scan of a region looked at, and why it stopped."""
    return _shot(s, d).highlights.select("session_id", "roi_id", "k_prime", "scanned", "stop_reason").distinct()


@query
def q_sequence(s, d):
    return sequence.sequence(_shot(s, d).highlights, facets.carrier(s, d)).select("session_id", "step", "poi_id", *_six("leg"))


@query
def q_choose(s, d):
    spread = sequence.dispersion(_rois(s, d))
    return spread.select("session_id", *_six("dispersion"), sequence.choose(F.col("dispersion"), 4).alias("approach"))


def _random(s, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(regions, POIs, highlights another engine can also derive: k points a region by a fixed hash)."""
    r, p = _regions(s, d)
    return r, p, written(inside.first_k(r, p, baselines.RANDOM, 5), "random")


@query
def q_random_k(s, d):
    return _random(s, d)[2].select("session_id", "roi_id", "rank", "poi_id")


@query
def q_diversity(s, d):
    _, p, h = _random(s, d)
    return measures.diversity(h, facets.facets(p), len(facets.attributes(p))).select("session_id", "roi_id", *_six("diversity"))


def _click_truth(s, d) -> DataFrame:
    return sources.clicks(s, d).select("session_id", "poi_id").distinct()


@query
def q_precision(s, d):
    return measures.precision(_random(s, d)[2], _click_truth(s, d)).select("session_id", *_six("precision"))


@query
def q_hit_ratio(s, d):
    return measures.hit_ratio(_random(s, d)[2], _click_truth(s, d)).select(*_six("hit_ratio"))


@query
def q_accumulated(s, d):
    """Precision of a session's regions in their order, with its running mean and sum."""
    by_region = _random(s, d)[2].withColumn("round", F.col("roi_id"))
    q = measures.accumulated(measures.precision(by_region, _click_truth(s, d)), "precision")
    return q.select("session_id", "round", *_six("precision", "running_mean", "running_sum"))


@query
def q_objective(s, d):
    """The weighted sum that fuzzy highlights aim at, for highlights that another engine can also derive."""
    _, r, p, w = _weights(s, d)
    n = len(facets.attributes(p))
    m, f = written(match.match(r, p, quadtree.build(p)), "matched"), facets.facets(p)
    h = baselines.random_k(m).join(relevance.relevance(m, f, w, n, False), ["session_id", "roi_id", "poi_id"])
    return measures.objective(h, fuzzy.cohesiveness(m, f, n), fuzzy.representativeness(r)).select("session_id", F.round("objective", 4).alias("objective"))


@query
def q_coverage(s, d):
    r, _, h = _random(s, d)
    return measures.coverage(h, r).select("session_id", *_six("coverage"))


@query
def q_cohesiveness(s, d):
    c, _, p = _counts(s, d)
    return fuzzy.cohesiveness_of(c, len(facets.attributes(p))).select("session_id", "roi_id", *_six("cohesiveness"))


@query
def q_representativeness(s, d):
    return fuzzy.representativeness(_rois(s, d)).select("session_id", F.round("representativeness", 4).alias("representativeness"))


@query
def q_thinning_ratio(s, d):
    return measures.thinning(sources.moves(s, d), _kept(s, d)).select("session_id", "raw", "kept", *_six("ratio"))


@query
def q_prune_ratio(s, d):
    c = written(_clustered(s, d), "clustered")
    return measures.prune_ratio(c, hull.prune(c, 8), hull.convex_hull(c)).select("points", "left", "vertices", *_six("left_ratio", "vertex_ratio"))


@query
def q_peculiarity_report(s, d):
    return measures.peculiarity_report(_shot(s, d).k_primes).select("rois", *_six("p10", "p50", "p90", "mean_k"), "min_k", "max_k")


@query
def q_click_only(s, d):
    p = facets.carrier(s, d)
    return baselines.click_only(sources.clicks(s, d), p).select("session_id", "rank", "poi_id", *_six("relevance"))


@query
def q_nearest_k(s, d):
    m, p, _ = _matched(s, d)
    return baselines.nearest_k(m, p, _rois(s, d)).select("session_id", "roi_id", "rank", "poi_id")


@query
def q_popular_k(s, d):
    return baselines.popular_k(sources.clicks(s, d))


@query
def q_fused(s, d):
    return _rounded(baselines.fused(s, d))


@query
def q_greedy_vs_fuzzy(s, d):
    return baselines.compare(_shot(s, d).highlights, _shot(s, d, Params(), "fuzzy").highlights)


@query
def q_base_static(s, d):
    return workloads.static_preferences(s, d).select("round", "session_id", "roi_id", "rank", "poi_id", *_six("relevance"))


def _baseline(name: str) -> Query:
    def run(s, d):
        return _rounded(baselines.run(s, d, name))

    run.__name__ = f"q_base_{name}"
    return query(run)


for _name in baselines.SETTINGS:
    _baseline(_name)


# ---- workloads


@query
def q_single_shot_runs(s, d):
    return workloads.single_shot_runs(s, d)


@query
def q_scenario(s, d):
    return workloads.scenario(s, d).select("session_id", "n", *_six("near_share"))


@query
def q_worked_regions(s, d):
    return workloads.worked_regions(s)


@query
def q_known_facet(s, d):
    return workloads.known_facet(s, d)


@query
def q_eps_sweep(s, d):
    return workloads.eps_sweep(s, d).select("eps_ms", "kept", *_six("ratio"), "rois", F.round("roi_area", 3).alias("roi_area"))


@query
def q_cohort_compare(s, d):
    return workloads.cohort_compare(s, d)


@query
def q_layer_corr(s, d):
    return workloads.layer_corr(s, d)


@query
def q_track_summary(s, d):
    return workloads.track_summary(s, d)


@query
def q_track_focus(s, d):
    return workloads.track_focus(s, d)


@query
def q_brush(s, d):
    return workloads.brush(s, d)


@query
def q_band_dwell(s, d):
    return workloads.band_dwell(s, d)


@query
def q_day_plan(s, d):
    return workloads.day_plan(s, d)


@query
def q_replace_poi(s, d):
    return workloads.replace_poi(s, d)


@query
def q_preliminary_query(s, d):
    return _rounded(workloads.preliminary_query(s, d))


@query
def q_index_scale(s, d):
    return workloads.index_scale(s, d).select("candidates", "exact_tests", *_six("of_scan", "of_candidates"))


@query
def q_index_against_scan(s, d):
    return workloads.index_against_scan(s, d)


@query
def q_perception(s, d):
    return workloads.perception(s, d).select("session_id", *_six("perception"))


@query
def q_choose_study(s, d):
    return workloads.choose_study(s, d).select("phase", "approach", *_six("coverage", "diversity", "relevance", "cohesiveness"))


@query
def q_multi_shot(s, d):
    return workloads.multi_shot(s, d).select("round", *_six("confidence", "peculiarity", "k_prime"), "highlights")


@query
def q_simulate(s, d):
    return workloads.agents(s, d).select("session_id", "round", *_six("precision"), "hit", *_six("diversity", "acc_precision", "acc_hit", "acc_diversity"))


@query
def q_generic_customer(s, d):
    return _rounded(workloads.generic(s, d, "customer"))


@query
def q_generic_voice(s, d):
    """Voice commands move on with the turns, so their clusters do not meet: every hull is a region."""
    return _rounded(workloads.generic(s, d, "part", "voice", Params(min_pts=3, min_support=1)))


def _generic(name: str) -> Query:
    def run(s, d):
        return _rounded(workloads.generic(s, d, name))

    run.__name__ = f"q_generic_{name}"
    return query(run)


for _name in ("supplier", "orders", "embeddings", "pages", "benchmark"):
    _generic(_name)


def _sweep(name: str, suffix: str) -> Query:
    def run(s, d):
        return workloads.sweep(s, d, (name,)).select("parameter", "value", "rois", "highlights", *_six("relevance", "diversity"))

    run.__name__ = f"q_sweep{suffix}"
    return query(run)


for _name in workloads.SWEEPS:
    _sweep(_name, "" if _name == "k" else f"_{_name}")


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: one shot with printed peculiarity at k = 5."""
    return pipeline.single_shot(spark, sf_dir).withColumn("relevance", F.round("relevance", 6))


def queries() -> dict[str, Query]:
    return {"single_shot": entry} | QUERIES | OPS
