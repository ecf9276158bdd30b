"""Measures of cost and accuracy over highlights, truth and the stages' tables."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..geo import polygon
from ..suggest import peculiarity


def timed(spark: SparkSession, stages: dict[str, Callable[[], DataFrame]], runs: int = 3) -> DataFrame:
    """(stage, run, ms): each stage run into a sink that keeps nothing."""
    rows = []
    for run in range(runs):
        for name, make in stages.items():
            t = time.monotonic()
            make().write.format("noop").mode("overwrite").save()
            rows.append((name, run, 1000 * (time.monotonic() - t)))
    return spark.createDataFrame(rows, "stage string, run int, ms double")


def memory(spark: SparkSession, stages: dict[str, Callable[[], DataFrame]]) -> DataFrame:
    """(stage, peak_bytes): peak of the JVM's memory pools while a stage runs, on the driver's JVM.

    In local mode that JVM also runs the tasks; on a cluster the executors' figures are in the event log.
    """
    pools = list(spark._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans())
    rows = []
    for name, make in stages.items():
        for p in pools:
            p.resetPeakUsage()
        make().write.format("noop").mode("overwrite").save()
        rows.append((name, sum(int(p.getPeakUsage().getUsed()) for p in pools)))
    return spark.createDataFrame(rows, "stage string, peak_bytes long")


def fluidity(times: DataFrame, limit_ms: float = 500.0) -> DataFrame:
    """(stage, share): runs of a stage within the limit."""
    return times.groupBy("stage").agg(F.avg((F.col("ms") <= limit_ms).cast("double")).alias("share"))


def _rounds(h: DataFrame) -> list[str]:
    return ["session_id", "round"] if "round" in h.columns else ["session_id"]


def precision(h: DataFrame, truth: DataFrame) -> DataFrame:
    """(session_id[, round], precision): relevant highlights over highlights; no row without highlights."""
    keys = _rounds(h)
    t = truth.select("session_id", "poi_id", F.lit(1.0).alias("_hit")).distinct()
    return h.join(t, ["session_id", "poi_id"], "left").groupBy(*keys).agg(F.avg(F.coalesce("_hit", F.lit(0.0))).alias("precision"))


def hit_ratio(h: DataFrame, truth: DataFrame, asked: DataFrame | None = None) -> DataFrame:
    """(hit_ratio,): session-rounds with a relevant highlight over all asked; those without highlights are no hits."""
    keys = _rounds(h)
    hit = precision(h, truth).withColumn("_h", (F.col("precision") > 0).cast("double"))
    if asked is not None:
        hit = asked.select(*keys).distinct().join(hit, keys, "left")
    return hit.agg(F.avg(F.coalesce("_h", F.lit(0.0))).alias("hit_ratio"))


def diversity(h: DataFrame, facets: DataFrame, n_attrs: int) -> DataFrame:
    """(session_id[, round], roi_id, diversity): mean cosine distance over pairs of a region's highlights; 0 below two.

    By facet counts: shared values of all pairs are sums of c*(c-1)/2, so nothing is paired.
    """
    keys = [*_rounds(h), "roi_id"]
    n = h.groupBy(*keys).agg(F.count("*").alias("n"))
    same = h.join(facets, "poi_id").groupBy(*keys, "attr", "val").agg(F.count("*").alias("c"))
    pairs = same.groupBy(*keys).agg(F.sum(F.expr("c * (c - 1) / 2")).alias("s"))
    d = 1 - F.col("s") / (F.lit(float(n_attrs)) * F.expr("n * (n - 1) / 2"))
    return n.join(pairs, keys, "left").select(*keys, F.when(F.col("n") < 2, 0.0).otherwise(d).alias("diversity"))


def accumulated(quality: DataFrame, value: str) -> DataFrame:
    """quality (session_id, round, value) with its running mean and sum."""
    w = W.partitionBy("session_id").orderBy("round").rowsBetween(W.unboundedPreceding, W.currentRow)
    return quality.withColumn("running_mean", F.avg(value).over(w)).withColumn("running_sum", F.sum(value).over(w))


def mean_relevance(h: DataFrame) -> DataFrame:
    return h.groupBy(*_rounds(h)).agg(F.avg("relevance").alias("mean_relevance"))


def objective(h: DataFrame, cohesion: DataFrame, representation: DataFrame, weights: tuple[float, float, float] = (0.5, 0.25, 0.25)) -> DataFrame:
    """(session_id, objective): the weighted sum of mean relevance, mean cohesiveness and representativeness."""
    w1, w2, w3 = weights
    c = cohesion.groupBy("session_id").agg(F.avg("cohesiveness").alias("c"))
    r = mean_relevance(h).groupBy("session_id").agg(F.avg("mean_relevance").alias("m"))
    return r.join(c, "session_id").join(representation, "session_id").select("session_id", (w1 * F.col("m") + w2 * F.col("c") + w3 * F.col("representativeness")).alias("objective"))


def coverage(h: DataFrame, rois: DataFrame) -> DataFrame:
    """(session_id, coverage): regions with a highlight over regions."""
    got = h.select("session_id", "roi_id").distinct().withColumn("_g", F.lit(1.0))
    return rois.select("session_id", "roi_id").join(got, ["session_id", "roi_id"], "left").groupBy("session_id").agg(F.avg(F.coalesce("_g", F.lit(0.0))).alias("coverage"))


def thinning(raw: DataFrame, kept: DataFrame) -> DataFrame:
    """(session_id, raw, kept, ratio)."""
    a = raw.groupBy("session_id").agg(F.count("*").alias("raw"))
    return a.join(kept.groupBy("session_id").agg(F.count("*").alias("kept")), "session_id").withColumn("ratio", F.col("kept") / F.col("raw"))


def prune_ratio(clustered: DataFrame, pruned: DataFrame, hulls: DataFrame) -> DataFrame:
    """(points, left, vertices, left_ratio, vertex_ratio) over all clusters."""
    n = clustered.where("cluster_id is not null").agg(F.count("*").alias("points"))
    v = hulls.agg(F.sum(F.size("poly")).alias("vertices"))
    return n.join(pruned.agg(F.count("*").alias("left"))).join(v).select("points", "left", "vertices", (F.col("left") / F.col("points")).alias("left_ratio"), (F.col("vertices") / F.col("points")).alias("vertex_ratio"))


def selectivity(candidates: DataFrame, n_pois: int, n_rois: int) -> DataFrame:
    """(candidates, exact_tests, of_scan, of_candidates): what the index leaves of a scan of every POI for every region."""
    c = candidates.agg(F.count("*").alias("candidates"), F.count_if(~F.col("inside")).alias("exact_tests"))
    return c.select("candidates", "exact_tests", (F.col("candidates") / F.lit(float(max(1, n_pois * n_rois)))).alias("of_scan"), F.try_divide("exact_tests", "candidates").alias("of_candidates"))


def peculiarity_report(k_primes: DataFrame) -> DataFrame:
    """Distribution of peculiarity and k' over regions."""
    q = F.percentile("peculiarity", F.array(F.lit(0.1), F.lit(0.5), F.lit(0.9)))
    return k_primes.agg(F.count("*").alias("rois"), q.alias("q"), F.avg("k_prime").alias("mean_k"), F.min("k_prime").alias("min_k"), F.max("k_prime").alias("max_k")).select(
        "rois", F.col("q")[0].alias("p10"), F.col("q")[1].alias("p50"), F.col("q")[2].alias("p90"), "mean_k", "min_k", "max_k"
    )


def stretch_report(polys: DataFrame) -> DataFrame:
    """(session_id, confidence, ratio): mean new over old area of a session's stretched polygons."""
    return polys.where("area0 > 0").groupBy("session_id").agg(F.max("confidence").alias("confidence"), F.avg(F.col("area") / F.col("area0")).alias("ratio"))


def region_recovery(clustered: DataFrame, rois: DataFrame, spots: list[tuple[int, int]], reach: float = 60.0) -> DataFrame:
    """(session_id, purity, spots_found): share of clustered points in their cluster's main true spot; spots near a region's centre, of five."""
    c = clustered.where("cluster_id is not null and not true_noise").groupBy("session_id", "seg", "cluster_id", "true_spot").agg(F.count("*").alias("n"))
    best = c.groupBy("session_id", "seg", "cluster_id").agg(F.max("n").alias("m"), F.sum("n").alias("t"))
    purity = best.groupBy("session_id").agg((F.sum("m") / F.sum("t")).alias("purity"))
    centre = rois.withColumn("c", polygon.centroid(F.col("poly")))
    near = [F.max((F.hypot(F.col("c.x") - x, F.col("c.y") - y) <= reach).cast("int")) for x, y in spots]
    found = centre.groupBy("session_id").agg(sum(near[1:], near[0]).alias("spots_found"))
    return purity.join(found, "session_id", "left").fillna(0, ["spots_found"])


def perception_proxy(h: DataFrame, labels: DataFrame) -> DataFrame:
    """(session_id, perception): mean quality label of highlighted documents that are labelled."""
    lab = labels.select(F.col("doc_id").alias("poi_id"), "quality")
    return h.join(lab, "poi_id").groupBy("session_id").agg(F.avg("quality").alias("perception"))


def roi_alignment(vectors: DataFrame, weights: DataFrame, per_roi: bool = True) -> DataFrame:
    """(session_id, roi_id, alignment): cosine of the feedback and a region's binary vector."""
    return peculiarity.score(vectors, weights, per_roi).select("session_id", "roi_id", F.col("printed").alias("alignment"))


def mine_report(clustered: DataFrame) -> DataFrame:
    """(session_id, segments, clusters, noise_share)."""
    per = clustered.groupBy("session_id", "seg").agg(F.count_distinct("cluster_id").alias("c"), F.count("*").alias("n"), F.count_if(F.col("cluster_id").isNull()).alias("z"))
    return per.groupBy("session_id").agg(F.count("*").alias("segments"), F.sum("c").alias("clusters"), (F.sum("z") / F.sum("n")).alias("noise_share"))


def entropy(vector: DataFrame) -> DataFrame:
    """(session_id, entropy): spread of softmax weights over touched cells."""
    return vector.groupBy("session_id").agg((-F.sum(F.col("weight") * F.ln("weight"))).alias("entropy"))

