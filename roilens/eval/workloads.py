"""The paper's experiment workloads and domain scenes on the given tables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .. import pipeline
from ..collect import segment, sources, thin
from ..geo import polygon, quadtree
from ..mine import hull, intersect, personalize
from ..params import Params
from ..storage import table, written
from ..suggest import facets, feedback, fuzzy, inside, match, peculiarity, relevance, sequence
from . import measures


def single_shot_runs(spark: SparkSession, sf_dir: str, params: Params = Params(), runs: int = 3) -> DataFrame:
    """(component, mean_ms, fluid_share, peak_bytes): time of each component over several runs, the share within 500 ms, memory."""
    pois = facets.carrier(spark, sf_dir)
    leaves = written(quadtree.build(pois, params.capacity, params.max_depth), "leaves")
    seg = written(pipeline.collect(sources.moves(spark, sf_dir), params), "segmented")
    rois = written(intersect.discover(seg, params), "rois")
    components = {
        "collect": lambda: pipeline.collect(sources.moves(spark, sf_dir), params),
        "mine": lambda: intersect.discover(seg, params),
        "suggest": lambda: pipeline.suggest(rois, pois, params, None, leaves)[-1],
    }
    times = measures.timed(spark, components, runs)
    mean = times.groupBy("stage").agg(F.avg("ms").alias("mean_ms"))
    fluid = measures.fluidity(times).withColumnRenamed("share", "fluid_share")
    return mean.join(fluid, "stage").join(measures.memory(spark, components), "stage").withColumnRenamed("stage", "component")


def hidden(moves: DataFrame, pois: DataFrame, least: float = 0.3) -> DataFrame:
    """(session_id, poi_id): what each virtual agent would accept: POIs of its hidden brand or type.

    An agent's hidden facets are brand s % 25 and type s % 6 in order of name; similarity is shared
    values over sqrt(2 * attributes).
    """
    brands = pois.select("brand").distinct().withColumn("i", F.row_number().over(W.orderBy("brand")) - 1)
    types = pois.select("type").distinct().withColumn("j", F.row_number().over(W.orderBy("type")) - 1)
    nb, nt = brands.count(), types.count()
    s = moves.select("session_id").distinct()
    want = s.join(brands, F.col("session_id") % nb == F.col("i")).join(types, F.col("session_id") % nt == F.col("j")).select("session_id", F.col("brand").alias("hb"), F.col("type").alias("ht"))
    n = len(facets.attributes(pois))
    # agents meet POIs by brand or by type: two equi-joins, no product
    by_brand = want.join(pois, F.col("hb") == F.col("brand")).select("session_id", "poi_id")
    by_type = want.join(pois, F.col("ht") == F.col("type")).select("session_id", "poi_id")
    shared = by_brand.unionAll(by_type).groupBy("session_id", "poi_id").agg(F.count("*").alias("c"))
    return shared.where(F.col("c") / F.sqrt(F.lit(2.0 * n)) >= least).select("session_id", "poi_id")


def agents(spark: SparkSession, sf_dir: str, params: Params = Params(), rounds: int = 5, approach: str = "greedy", per_round: int = 120) -> DataFrame:
    """(session_id, round, precision, hit, diversity, with running means): a simulation with virtual agents.

    In each round an agent moves near POIs it likes, amid noise; it accepts highlights it likes.  All
    agents are rows of one table.
    """
    pois = written(facets.carrier(spark, sf_dir), "pois")
    noise = sources.moves(spark, sf_dir).where("true_noise").select("session_id", "event_id", "t_ms", "x", "y", "signal")
    liked = written(hidden(sources.moves(spark, sf_dir), pois), "liked")
    # places where several liked POIs lie close together come first, as a user lingers there
    spots = liked.join(pois.select("poi_id", "mx", "my"), "poi_id").withColumn("rank", F.row_number().over(W.partitionBy("session_id").orderBy(F.floor(F.col("mx") / 60), F.floor(F.col("my") / 60), "poi_id")))
    spots = written(spots.where(F.col("rank") <= per_round // 6), "spots")
    by_round = []
    for r in range(1, rounds + 1):
        near = spots.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(5)))).select(
            "session_id",
            (F.col("rank") * 100 + F.col("i") + r * 100_000_000).alias("event_id"),
            ((F.col("rank") * 6 + F.col("i")) * 30_000 / per_round).cast("long").alias("t_ms"),
            (F.col("mx") + (F.col("i") * 7 + r * 7) % 11 - 5).alias("x"),
            (F.col("my") + (F.col("i") * 5 + r * 3) % 11 - 5).alias("y"),
            F.lit("hover").alias("signal"),
        )
        by_round.append(written(near.unionByName(noise.where(F.col("event_id") % rounds == r - 1)), "round"))
    found, _ = pipeline.iterate(spark, by_round, pois, params, None, approach)
    found = written(found, "found")
    asked = liked.select("session_id").distinct().withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds))))
    q = asked.join(measures.precision(found, liked), ["session_id", "round"], "left")
    d = measures.diversity(found, facets.facets(pois), len(facets.attributes(pois))).groupBy("session_id", "round").agg(F.avg("diversity").alias("diversity"))
    q = q.join(d, ["session_id", "round"], "left").withColumn("hit", (F.coalesce("precision", F.lit(0.0)) > 0).cast("int"))
    w = W.partitionBy("session_id").orderBy("round").rowsBetween(W.unboundedPreceding, 0)
    return q.select("session_id", "round", "precision", "hit", "diversity", F.avg("precision").over(w).alias("acc_precision"), F.avg("hit").over(w).alias("acc_hit"), F.avg("diversity").over(w).alias("acc_diversity"))


def perception(spark: SparkSession, sf_dir: str, params: Params = Params()) -> DataFrame:
    """Stand-in for a user study: mean quality label of highlighted documents."""
    h = pipeline.single_shot(spark, sf_dir, params, "greedy", "documents")
    return measures.perception_proxy(h, table(spark, sf_dir, "labels"))


def scenario(spark: SparkSession, sf_dir: str, params: Params = Params()) -> DataFrame:
    """1500 results, hovering near one landmark, no click: highlights should lie around it.

    (session_id, n, near_share): highlights and the share within 200 px of the landmark.
    """
    pois = facets.carrier(spark, sf_dir).where("poi_id < 1500")
    moves = sources.moves(spark, sf_dir, spots=0)
    h = pipeline.shot(moves, pois, params).highlights.join(pois.select("poi_id", "mx", "my"), "poi_id")
    d = F.hypot(F.col("mx") - sources.ANCHOR_X[0], F.col("my") - sources.ANCHOR_Y[0])
    return h.groupBy("session_id").agg(F.count("*").alias("n"), F.avg((d <= 200).cast("double")).alias("near_share"))


# The six hulls of the worked example, as segment, cluster, x0, x1, y0, y1.
WORKED = ((0, 1, 0, 10, 0, 10), (0, 2, 40, 50, 0, 10), (1, 3, 5, 15, -5, 5), (1, 4, 45, 55, 5, 15), (2, 5, 12, 22, -10, 0), (2, 6, 52, 60, 12, 20))


def worked_regions(spark: SparkSession, mode: str = "none", conf: float = 1.0) -> DataFrame:
    """(src_a, src_b, area): regions of the worked example under a stretch mode."""
    rows = [(0, s, c, [(float(a), float(e)), (float(b), float(e)), (float(b), float(f)), (float(a), float(f))], conf) for s, c, a, b, e, f in WORKED]
    polys = spark.createDataFrame(rows, f"session_id long, seg int, cluster_id long, poly {polygon.POLYGON}, confidence double")
    r = intersect.rois(personalize.stretch(hull.with_measures(polys), mode))
    return r.select(F.col("src")[0].alias("src_a"), F.col("src")[1].alias("src_b"), F.round("area", 6).alias("area"))


def confidence_curve(spark: SparkSession, sf_dir: str, xi: float = 7.0) -> DataFrame:
    """(nnz, t, confidence): the numbers of facets that customers' orders touch, none included, against a grid of interactions."""
    orders = table(spark, sf_dir, "orders").groupBy("o_custkey").agg((F.count_distinct("o_orderstatus") + F.count_distinct("o_orderpriority")).alias("touched"))
    customers = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"))
    nnz = customers.join(orders, "o_custkey", "left").select(F.coalesce("touched", F.lit(0)).alias("nnz")).distinct()
    grid = nnz.withColumn("t", F.explode(F.array(*map(F.lit, (0, 1, 2, 5, 10, 20)))))
    return grid.withColumn("confidence", F.round(personalize.confidence(F.col("nnz"), F.col("t"), xi), 6))


def eps_sweep(spark: SparkSession, sf_dir: str, gaps: tuple[int, ...] = (1, 10, 50, 100, 250, 1000), params: Params = Params()) -> DataFrame:
    """(eps_ms, kept, ratio, rois, roi_area): sampling gap against what is kept and found, sessions of 128 users.

    All gaps go through the stages together: a session at a gap is a session of its own.  Cells of a gap are
    unions of cells of any gap that divides it, so their first moves are found among that gap's.
    """
    moves = written(sources.moves(spark, sf_dir, users_per_session=128), "dense-moves")
    n, kept = moves.count(), {}
    for eps in sorted(set(gaps)):
        finer = max((g for g in kept if eps % g == 0), default=None)
        kept[eps] = written(thin.grid(moves if finer is None else kept[finer], eps), "kept")
    gap = F.pmod("session_id", F.lit(len(kept)))
    at = [kept[eps].withColumn("session_id", F.col("session_id") * len(kept) + i) for i, eps in enumerate(kept)]
    found = intersect.discover(segment.segment(reduce(DataFrame.unionByName, at), params), params)
    found = written(found.groupBy(gap.cast("int").alias("gap")).agg(F.count("*").alias("rois"), F.sum("area").alias("roi_area")), "by-gap")
    out = []
    for eps in gaps:
        r = found.where(F.col("gap") == list(kept).index(eps)).agg(F.coalesce(F.sum("rois"), F.lit(0)).alias("rois"), F.sum("roi_area").alias("roi_area"))
        out.append(kept[eps].agg(F.count("*").alias("kept")).join(r).select(F.lit(eps).alias("eps_ms"), "kept", (F.col("kept") / F.lit(float(max(n, 1)))).alias("ratio"), "rois", "roi_area"))
    return reduce(DataFrame.unionByName, out)


def known_facet(spark: SparkSession, sf_dir: str, params: Params = Params()) -> DataFrame:
    """(roi_kind, printed, intent): peculiarity of a region of one known size decade against one of all, feedback saturated on it."""
    pois = facets.carrier(spark, sf_dir)
    fr = facets.facets(pois)
    m = pois.select(F.lit(0).cast("long").alias("session_id"), "poi_id", "size_decade")
    matched = m.where("size_decade = '0'").select("session_id", F.lit(1).alias("roi_id"), "poi_id").unionByName(m.select("session_id", F.lit(2).alias("roi_id"), "poi_id"))
    raw = spark.createDataFrame([(0, "size_decade", "0", 10.0)], "session_id long, attr string, val string, raw double")
    only = fr.where("attr = 'size_decade'")
    w = feedback.softmax(raw, facets.dictionary(only).count())
    p = peculiarity.score(facets.roi_vector(matched, only), w, False)
    return p.select(F.when(F.col("roi_id") == 1, "known").otherwise("mixed").alias("roi_kind"), F.round("printed", 6).alias("printed"), F.round("intent", 6).alias("intent"))


def cohort_compare(spark: SparkSession, sf_dir: str, nation: int = 7) -> DataFrame:
    """(segment, share_region, share_all, balance_region, balance_all): one region's cohort against the whole."""
    c = table(spark, sf_dir, "customer").select("c_mktsegment", "c_acctbal", (F.col("c_nationkey") == nation).alias("here"))
    g = c.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count_if("here").alias("h"), F.count("*").alias("n"), F.avg(F.when(F.col("here"), F.col("c_acctbal"))).alias("bh"), F.avg("c_acctbal").alias("b"))
    w = W.partitionBy()
    return g.select("segment", F.round(F.col("h") / F.sum("h").over(w), 6).alias("share_region"), F.round(F.col("n") / F.sum("n").over(w), 6).alias("share_all"), F.round("bh", 4).alias("balance_region"), F.round("b", 4).alias("balance_all"))


def layer_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(corr,): correlation of two layers, mean customer and supplier balance by nation."""
    c = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.avg("c_acctbal").alias("a"))
    s = table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.avg("s_acctbal").alias("b"))
    return c.join(s, "k").agg(F.round(F.corr("a", "b"), 6).alias("corr"))


def track_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(track_id, first_id, last_id, points, length): what a click on a trajectory shows."""
    t = sources.tracks(spark, sf_dir)
    w = W.partitionBy("track_id").orderBy("t_ms", "event_id")
    step = F.hypot(F.col("x") - F.lag("x").over(w), F.col("y") - F.lag("y").over(w))
    k = F.struct("t_ms", "event_id")
    return t.withColumn("d", step).groupBy("track_id").agg(F.min_by("event_id", k).alias("first_id"), F.max_by("event_id", k).alias("last_id"), F.count("*").alias("points"), F.round(F.coalesce(F.sum("d"), F.lit(0.0)), 4).alias("length"))


def track_focus(spark: SparkSession, sf_dir: str, track: int = 3) -> DataFrame:
    """One trajectory alone, in order."""
    t = sources.tracks(spark, sf_dir).where(F.col("track_id") == track)
    return t.select("event_id", "t_ms", "x", "y", F.row_number().over(W.partitionBy("track_id").orderBy("t_ms", "event_id")).alias("step"))


def brush(spark: SparkSession, sf_dir: str, t0: int = 5000, t1: int = 20000, x0: int = -300, x1: int = 300, y0: int = -200, y1: int = 200) -> DataFrame:
    """(track_id, n): points of trajectories inside a brushed box of place and time."""
    t = sources.tracks(spark, sf_dir).where(F.col("t_ms").between(t0, t1) & F.col("x").between(x0, x1) & F.col("y").between(y0, y1))
    return t.groupBy("track_id").agg(F.count("*").alias("n"))


def band_dwell(spark: SparkSession, sf_dir: str, band: int = 50) -> DataFrame:
    """(band, dwell_ms, looks): time until the next signal, by altitude band."""
    t = sources.tracks(spark, sf_dir)
    w = W.partitionBy("track_id").orderBy("t_ms", "event_id")
    return t.withColumn("dwell", F.lead("t_ms").over(w) - F.col("t_ms")).groupBy(F.floor(F.col("alt") / band).alias("band")).agg(F.sum("dwell").alias("dwell_ms"), F.count("*").alias("looks"))


def day_plan(spark: SparkSession, sf_dir: str, x0: int = -320, x1: int = -180, y0: int = 80, y1: int = 220) -> DataFrame:
    """(noun, poi_id): a plan for a dragged region, the cheapest POI of each kind."""
    p = facets.carrier(spark, sf_dir).where(F.col("mx").between(x0, x1) & F.col("my").between(y0, y1))
    price = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("poi_id"), "p_retailprice")
    w = W.partitionBy("noun").orderBy("p_retailprice", "poi_id")
    return p.join(price, "poi_id").withColumn("r", F.row_number().over(w)).where("r = 1").select("noun", "poi_id")


def replace_poi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(noun, old_id, new_id): for each POI of the plan, the most similar one of the region that the plan lacks."""
    p = facets.carrier(spark, sf_dir).where(F.col("mx").between(-320, -180) & F.col("my").between(80, 220))
    attrs = facets.attributes(p)
    plan = day_plan(spark, sf_dir)
    old = plan.select(F.col("poi_id").alias("old_id")).join(p, F.col("old_id") == F.col("poi_id")).drop("poi_id")
    rest = p.join(plan.select("poi_id"), "poi_id", "left_anti")
    j = old.alias("a").join(rest.alias("b"), F.col("a.noun") == F.col("b.noun"))
    w = W.partitionBy("old_id").orderBy(F.col("sim").desc(), F.col("new_id"))
    scored = j.select("old_id", F.col("a.noun").alias("noun"), F.col("b.poi_id").alias("new_id"), relevance.poi_cosine(attrs).alias("sim"))
    return scored.withColumn("r", F.row_number().over(w)).where("r = 1").select("noun", "old_id", "new_id")


def choose_study(spark: SparkSession, sf_dir: str, params: Params = Params()) -> DataFrame:
    """(phase, approach, coverage, diversity, relevance, cohesiveness): both approaches on wide and on focused sessions."""
    pois = written(facets.carrier(spark, sf_dir), "pois")
    s = pipeline.shot(sources.moves(spark, sf_dir), pois, params)
    attrs, fr = facets.attributes(pois), facets.facets(pois)
    other = written(inside.fuzzy_highlight(s.rois, pois, attrs, s.weights, s.k_primes, params, "roi_id" in s.weights.columns), "fuzzy")
    spread = written(sequence.dispersion(s.rois, params), "spread")
    middle = spread.agg(F.percentile("dispersion", 0.5)).first()[0]
    phase = spread.select("session_id", F.when(F.col("dispersion") >= middle, "wide").otherwise("focused").alias("phase"))
    out = []
    for name, h in (("greedy", s.highlights), ("fuzzy", other)):
        parts = [
            measures.coverage(h, s.rois),
            measures.diversity(h, fr, len(attrs)).groupBy("session_id").agg(F.avg("diversity").alias("diversity")),
            measures.mean_relevance(h),
            fuzzy.cohesiveness(h.select("session_id", "roi_id", "poi_id"), fr, len(attrs)).groupBy("session_id").agg(F.avg("cohesiveness").alias("cohesiveness")),
        ]
        joined = reduce(lambda a, b: a.join(b, "session_id", "left"), parts, phase)
        out.append(joined.groupBy("phase").agg(F.avg("coverage").alias("coverage"), F.avg("diversity").alias("diversity"), F.avg("mean_relevance").alias("relevance"), F.avg("cohesiveness").alias("cohesiveness")).withColumn("approach", F.lit(name)))
    return out[0].unionByName(out[1])


#: One-parameter sweeps: name -> values.
SWEEPS = {
    "k": (1, 3, 5, 10), "threshold": (0.0, 0.2, 0.4, 0.6), "delta": (0.01, 0.05, 0.2), "eps_ms": (50, 100, 250), "g": (1, 2, 3, 6),
    "radius": (15.0, 30.0, 45.0), "min_pts": (3, 5, 8), "xi": (1.0, 7.0, 30.0), "weights": ((1.0, 0.0, 0.0), (0.5, 0.25, 0.25), (0.0, 1.0, 0.0)), "capacity": (16, 64, 256),
}


def sweep(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("k", "threshold"), params: Params = Params()) -> DataFrame:
    """(parameter, value, rois, highlights, relevance, diversity): how each measure moves with each parameter."""
    pois = written(facets.carrier(spark, sf_dir), "pois")
    fr, n = facets.facets(pois), len(facets.attributes(pois))
    moves = written(sources.moves(spark, sf_dir), "moves")
    out = []
    for name in names:
        for value in SWEEPS[name]:
            s = pipeline.shot(moves, pois, params.but(**{name: value}), None, "fuzzy" if name == "weights" else "greedy")
            h = s.highlights
            d = measures.diversity(h, fr, n).agg(F.avg("diversity").alias("diversity"))
            row = h.agg(F.count("*").alias("highlights"), F.avg("relevance").alias("relevance")).join(d).join(s.rois.agg(F.count("*").alias("rois")))
            out.append(row.select(F.lit(name).alias("parameter"), F.lit(str(value)).alias("value"), "rois", "highlights", "relevance", "diversity"))
    return reduce(DataFrame.unionByName, out)


def preliminary_query(spark: SparkSession, sf_dir: str, params: Params = Params()) -> DataFrame:
    """Highlights among the results of a query on size and price."""
    keep = table(spark, sf_dir, "part").where("p_size <= 30 and p_retailprice < 1500").select(F.col("p_partkey").alias("poi_id"))
    pois = facets.carrier(spark, sf_dir).join(keep, "poi_id", "left_semi")
    return pipeline.shot(sources.moves(spark, sf_dir), pois, params).highlights


def generic(spark: SparkSession, sf_dir: str, carrier: str = "customer", signal: str = "hover", params: Params = Params()) -> DataFrame:
    """The same pipeline on another POI set or another kind of signal."""
    moves = sources.voice(spark, sf_dir, 64, 40) if signal == "voice" else sources.moves(spark, sf_dir)
    return pipeline.shot(moves, facets.carrier(spark, sf_dir, carrier), params).highlights


def index_scale(spark: SparkSession, sf_dir: str, params: Params = Params(stretch="none")) -> DataFrame:
    """(candidates, exact_tests, of_scan, of_candidates) with lines of orders as POIs."""
    pois = written(facets.carrier(spark, sf_dir, "lineitem").select("poi_id", "mx", "my"), "scale-pois")
    leaves = written(quadtree.build(pois, params.capacity, params.max_depth), "leaves")
    rois = written(intersect.discover(pipeline.collect(sources.moves(spark, sf_dir), params), params), "rois")
    return measures.selectivity(match.candidates(rois, pois, leaves), pois.count(), rois.count())


def index_against_scan(spark: SparkSession, sf_dir: str, params: Params = Params(stretch="none")) -> DataFrame:
    """(way, met, matches): POIs that meet a region, and those inside, through the index and by the scan of all."""
    pois = written(facets.carrier(spark, sf_dir, "lineitem").select("poi_id", "mx", "my"), "scale-pois")
    leaves = written(quadtree.build(pois, params.capacity, params.max_depth), "leaves")
    rois = written(intersect.discover(pipeline.collect(sources.moves(spark, sf_dir), params), params), "rois")
    met = {"index": match.candidates(rois, pois, leaves).agg(F.count("*").alias("met")), "scan": spark.range(1).select(F.lit(pois.count() * rois.count()).alias("met"))}
    found = {"index": match.match(rois, pois, leaves), "scan": match.match(rois, pois)}
    return reduce(DataFrame.unionByName, [met[way].join(found[way].agg(F.count("*").alias("matches"))).select(F.lit(way).alias("way"), "met", "matches") for way in met])


def _weeks(spark: SparkSession, sf_dir: str, params: Params, rounds: int, freeze_after: int | None = None) -> tuple[DataFrame, list[pipeline.Shot]]:
    """Weeks of events as rounds, sessions of 32 users; a week takes the time of a session, so that thinning leaves enough of it."""
    moves = written(sources.moves(spark, sf_dir, users_per_session=32), "moves")
    week = params.horizon_ms // rounds
    by_round = [moves.where((F.col("t_ms") >= i * week) & (F.col("t_ms") < (i + 1) * week)).withColumn("t_ms", (F.col("t_ms") - i * week) * rounds) for i in range(rounds)]
    return pipeline.iterate(spark, by_round, written(facets.carrier(spark, sf_dir), "pois"), params, freeze_after)


def static_preferences(spark: SparkSession, sf_dir: str, params: Params = Params(), rounds: int = 2, freeze_after: int = 1) -> DataFrame:
    """Highlights by round where preferences are learnt at the start and then stay as they are."""
    return _weeks(spark, sf_dir, params, rounds, freeze_after)[0]


def multi_shot(spark: SparkSession, sf_dir: str, params: Params = Params(), rounds: int = 4) -> DataFrame:
    """(round, confidence, peculiarity, k_prime, highlights): weeks of events as rounds that carry the feedback."""
    _, shots = _weeks(spark, sf_dir, params, rounds)
    out = []
    for i, s in enumerate(shots, 1):
        conf = personalize.session_confidence(s.feedback, i, params.xi).agg(F.avg("confidence").alias("confidence"))
        k = s.k_primes.agg(F.avg("peculiarity").alias("peculiarity"), F.avg("k_prime").alias("k_prime"))
        out.append(conf.join(k).join(s.highlights.agg(F.count("*").alias("highlights"))).withColumn("round", F.lit(i)))
    return reduce(DataFrame.unionByName, out)
