"""What the methods stand against: other feedback, other stages, other selections."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .. import pipeline
from ..collect import sources
from ..geo import polygon
from ..params import Params
from ..storage import written
from ..suggest import facets, feedback

#: Facet combinations that a kernel scores at a time, about.
COMBOS = 50_000


def click_only(clicks: DataFrame, pois: DataFrame, k: int = 5, delta: float = 0.05) -> DataFrame:
    """(session_id, rank, poi_id, relevance): feedback from clicked POIs alone, no regions; the k most relevant POIs.

    Relevance depends on a POI's facets only, so sessions meet distinct facet combinations, not POIs.  Groups
    of sessions meet blocks of combinations in a kernel that keeps each session's k best, so no product of
    the two is ever a table.
    """
    attrs = facets.attributes(pois)
    fr = facets.facets(pois)
    raw = feedback.with_clicks(clicks.select("session_id", F.lit("").alias("attr"), F.lit("").alias("val"), F.lit(0.0).alias("raw")).limit(0), clicks, fr, delta)
    n_cells = facets.dictionary(fr).count()
    w = feedback.softmax(raw, n_cells)
    combos = pois.groupBy(*attrs).agg(F.array_sort(F.collect_list("poi_id")).alias("ids")).select(F.slice("ids", 1, k).alias("ids"), *attrs)
    combos = written(combos, "combos")
    groups = int(pois.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    blocks = 1 + combos.count() // COMBOS
    w = w.select(F.pmod(F.xxhash64("session_id"), F.lit(groups)).alias("g"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b"), "session_id", "attr", "val", "weight", "w0", "norm")
    dealt = combos.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("g"), F.pmod(F.xxhash64(*attrs), F.lit(blocks)).cast("int").alias("b"), "ids", *attrs)

    def kernel(of: pa.Table, there: pa.Table) -> pa.Table:
        out = []
        if of.num_rows and there.num_rows:
            first = np.array([x[0] for x in there.column("ids").to_pylist()])
            ids, codes = there.column("ids").to_pylist(), {}
            number = {}
            for name in attrs:  # every attribute's values are numbered, absent ones included
                d = there.column(name).combine_chunks().dictionary_encode(null_encoding="encode")
                codes[name], values = d.indices.to_numpy(), d.dictionary.to_pylist()
                number[name] = {v: i for i, v in enumerate(values)}
            t = of.sort_by("session_id")
            sid, attr, val = t.column("session_id").to_numpy(), t.column("attr").to_pylist(), t.column("val").to_pylist()
            weight, w0, norm = (t.column(c).to_numpy() for c in ("weight", "w0", "norm"))
            cuts = [0, *(np.flatnonzero(np.diff(sid)) + 1).tolist(), len(sid)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                vectors = {name: np.full(len(number[name]), w0[lo]) for name in attrs}
                for i in range(lo, hi):
                    n = number[attr[i]].get(val[i])
                    if n is not None:
                        vectors[attr[i]][n] = weight[i]
                like = sum(vectors[name][codes[name]] for name in attrs) / (norm[lo] * np.sqrt(len(attrs)))
                # a point among the k best has a combination whose first point is among the k best first points
                out += [(int(sid[lo]), p, float(like[c])) for c in np.lexsort([first, -np.round(like, 9)])[:k].tolist() for p in ids[c]]
        cols = list(zip(*out, strict=True)) or [()] * 3
        return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.float64()), strict=True)], ["session_id", "poi_id", "relevance"])

    top = w.groupBy("g", "b").cogroup(dealt.groupBy("g", "b")).applyInArrow(kernel, "session_id long, poi_id long, relevance double")
    rank = F.row_number().over(W.partitionBy("session_id").orderBy(F.round("relevance", 9).desc(), "poi_id"))
    return top.withColumn("rank", rank).where(F.col("rank") <= k).select("session_id", "rank", "poi_id", "relevance")


def fused(spark: SparkSession, sf_dir: str, params: Params = Params(), w_click: float = 0.05) -> DataFrame:
    """Highlights where clicks have taught the feedback before the moves do."""
    pois = facets.carrier(spark, sf_dir)
    empty = spark.createDataFrame([], "session_id long, attr string, val string, raw double")
    before = feedback.with_clicks(empty, sources.clicks(spark, sf_dir), facets.facets(pois), w_click)
    moves = sources.moves(spark, sf_dir)
    mine = before.join(moves.select("session_id").distinct(), "session_id", "left_semi")
    return pipeline.shot(moves, pois, params, mine).highlights


#: Baselines that are settings of the pipeline.
SETTINGS: dict[str, Params] = {
    "all_moves": Params(eps_ms=1),
    "no_segmentation": Params(g=1, min_support=1),
    "hulls_as_rois": Params(min_support=1),
    "tight_rois": Params(stretch="none"),
    "textbook_hull": Params(hull="angular", prune_directions=0),
    "plain_k": Params(peculiarity="plain"),
    "relevance_only": Params(max_scan=0),
    "diversity_only": Params(threshold=0.0),
    "scan": Params(use_index=False),
    "state_softmax": Params(softmax="state"),
    "per_value": Params(per="value"),
    "batch_update": Params(update="batch"),
}


def run(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Highlights of a named setting."""
    return pipeline.single_shot(spark, sf_dir, SETTINGS[name])


#: The order that picks points as by chance: a fixed integer hash of poi_id.
RANDOM = "(poi_id * 2654435761L + 1) % 4294967296L"


def random_k(matched: DataFrame, k: int = 5) -> DataFrame:
    """k points of each region by a fixed integer hash of poi_id."""
    w = W.partitionBy("session_id", "roi_id").orderBy(F.expr(RANDOM), "poi_id")
    return matched.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def nearest_k(matched: DataFrame, pois: DataFrame, rois: DataFrame, k: int = 5) -> DataFrame:
    """The k points of each region nearest to its centroid."""
    c = rois.select("session_id", "roi_id", polygon.centroid(F.col("poly")).alias("_c"))
    rows = matched.join(c, ["session_id", "roi_id"]).join(pois.select("poi_id", "mx", "my"), "poi_id")
    d = F.round(F.hypot(F.col("mx") - F.col("_c.x"), F.col("my") - F.col("_c.y")), 6)
    w = W.partitionBy("session_id", "roi_id").orderBy(d, "poi_id")
    return rows.withColumn("distance", d).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("session_id", "roi_id", "poi_id", "distance", "rank")


def popular_k(clicks: DataFrame, k: int = 5) -> DataFrame:
    """(rank, poi_id, n): the most clicked POIs, wherever they are."""
    top = clicks.groupBy("poi_id").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "poi_id").limit(k)
    return top.withColumn("rank", F.row_number().over(W.orderBy(F.col("n").desc(), "poi_id"))).select("rank", "poi_id", "n")


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """(session_id, both, only_a, only_b): how two runs' highlights overlap."""
    x = a.select("session_id", "roi_id", "poi_id").distinct().withColumn("_a", F.lit(1))
    y = b.select("session_id", "roi_id", "poi_id").distinct().withColumn("_b", F.lit(1))
    j = x.join(y, ["session_id", "roi_id", "poi_id"], "full")
    return j.groupBy("session_id").agg(F.count_if(F.col("_a").isNotNull() & F.col("_b").isNotNull()).alias("both"), F.count_if(F.col("_b").isNull()).alias("only_a"), F.count_if(F.col("_a").isNull()).alias("only_b"))
