"""Regions counted and ranked beside their points against the way through a row for each match."""

import pytest
from pyspark.sql import functions as F

from roilens import pipeline, queries
from roilens.collect import segment, sources, thin
from roilens.eval import baselines
from roilens.geo import quadtree
from roilens.mine import cluster, components, intersect
from roilens.params import Params
from roilens.relational.ops import OPS, SQL
from roilens.storage import written
from roilens.suggest import facets, feedback, fuzzy, inside, match, peculiarity, relevance


@pytest.fixture(scope="module")
def parts(spark, sf):
    r = written(intersect.discover(pipeline.collect(sources.moves(spark, sf)), Params()), "rois")
    p = written(facets.carrier(spark, sf).withColumn("brand", F.expr("if(poi_id % 7 = 0, null, brand)")), "pois")
    m = written(match.match(r, p, quadtree.build(p)), "matched")
    return r, p, m, written(facets.facets(p), "facets")


def rows(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_counts_are_those_of_matches(parts, monkeypatch):
    r, p, m, f = parts
    monkeypatch.setattr(inside, "REGIONS", 4)  # several kernel calls a tile
    c = written(inside.counts(r, p, facets.attributes(p)), "counts")
    assert rows(c.where("attr is not null")) == rows(m.join(f, "poi_id").groupBy("session_id", "roi_id", "attr", "val").count())
    assert rows(c.where("attr is null").select("session_id", "roi_id", "n")) == rows(m.groupBy("session_id", "roi_id").count())
    six = F.round("cohesiveness", 9)
    assert rows(fuzzy.cohesiveness_of(c, 5).select("session_id", "roi_id", six)) == rows(fuzzy.cohesiveness(m, f, 5).select("session_id", "roi_id", six))


def test_wide_regions_take_larger_tiles(spark, parts):
    _, p, _, _ = parts
    ring = [(-700.5, -400.25), (650.0, -300.0), (300.0, 420.0), (-690.0, 10.0)]
    r = written(spark.createDataFrame([(1, 1, ring), (1, 2, [(x / 3, y / 3) for x, y in ring]), (1, 3, ring[:2])], "session_id long, roi_id int, poly array<struct<x:double,y:double>>"), "wide")
    for boundary in (False, True):
        got = inside.counts(r, p, ["type"], boundary).where("attr is null").select("session_id", "roi_id", "n")
        assert rows(got) == rows(match.match(r, p, None, boundary).groupBy("session_id", "roi_id").count())


def test_first_and_best_points_of_regions(parts):
    r, p, m, f = parts
    at = ("session_id", "roi_id", "rank", "poi_id")
    assert rows(inside.first_k(r, p, baselines.RANDOM, 5).select(*at)) == rows(baselines.random_k(m).select(*at))
    w = written(feedback.softmax(feedback.batch(m, f), facets.dictionary(f).count()), "weights")
    k = written(peculiarity.score(facets.roi_vector(m, f), w, False).select("session_id", "roi_id", F.lit(3).alias("k_prime")), "k")
    want = relevance.ranked(relevance.relevance(m, f, w, 5, False)).where("rank <= 3")
    assert rows(inside.best(r, p, facets.attributes(p), w, k, False).select(*at)) == rows(want.select(*at))


@pytest.mark.parametrize("params", [Params(), Params(softmax="state", peculiarity="plain"), Params(max_scan=1, update="batch", swap="best"), Params(threshold=0.0, diversity="min", boundary=True)])
def test_greedy_shot_lists_no_match(spark, sf, params, monkeypatch):
    moves, pois = sources.moves(spark, sf), facets.carrier(spark, sf)
    listed = pipeline.shot(moves, pois, params, listed=True)
    labels = []
    monkeypatch.setattr(pipeline, "written", lambda df, label: labels.append(label) or written(df, label))
    s = pipeline.shot(moves, pois, params)
    assert not {"matched", "scored", "ranked", "facets"} & set(labels)
    for a, b, value in ((s.highlights, listed.highlights, "relevance"), (s.feedback, listed.feedback, "raw"), (s.k_primes, listed.k_primes, "printed")):
        keep = [F.round(c, 6).alias(c) if c == value else F.col(c) for c in b.columns if c not in ("intent", "peculiarity")]
        assert rows(a.select(*keep)) == rows(b.select(*keep))


@pytest.mark.parametrize("name", ["q_feedback_batch", "q_feedback_clicks", "q_feedback_decay", "q_feedback_explain", "q_feedback_per_value", "q_feedback_sequential", "q_feedback_state", "q_kprime", "q_greedy_seed", "q_cohesiveness", "q_coverage", "q_diversity", "q_hit_ratio", "q_accumulated"])
def test_queries_list_no_match(spark, sf, name, monkeypatch):
    def listed(*_):
        raise AssertionError("a row for each match")

    monkeypatch.setattr(match, "match", listed)
    assert queries.QUERIES[name](spark, sf).columns


def test_out_of_sight_parts_meet_squares_of_moves(spark, sf):
    plan = OPS["op_anti_outofsight"](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert "collect_list" in plan and "exists(" in plan


def test_out_of_sight_parts_need_no_broadcast(spark, sf, tmp_path):
    """Neither parts nor moves go through the driver, whatever size Spark expects; also with odd keys."""
    duckdb = pytest.importorskip("duckdb")
    spark.read.parquet(f"{sf}/part.parquet").withColumn("p_partkey", F.expr("if(p_partkey % 9 = 0, null, p_partkey div 2 - 40)")).write.parquet(f"{tmp_path}/part.parquet")
    spark.read.parquet(f"{sf}/events.parquet").withColumn("event_id", F.expr("if(event_id % 5 = 0, null, event_id - 500)")).write.parquet(f"{tmp_path}/events.parquet")
    for d, files in ((sf, ".parquet"), (tmp_path, ".parquet/*.parquet")):
        got = OPS["op_anti_outofsight"](spark, str(d))
        assert "Broadcast" not in got._jdf.queryExecution().sparkPlan().toString()
        with duckdb.connect() as con:
            for name in ("part", "events"):
                con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{d}/{name}{files}'")
            assert rows(got) == sorted(con.execute(SQL["op_anti_outofsight"]).fetchall(), key=repr)


@pytest.mark.parametrize("of, table", [(OPS["op_recursive_series"], "lineitem"), (queries.QUERIES["q_confidence"], "orders")])
def test_series_and_curve_read_a_table(spark, sf, of, table, monkeypatch):
    from roilens.eval import workloads
    from roilens.relational import ops

    read = []
    for module in (workloads, ops):
        was = module.table
        monkeypatch.setattr(module, "table", lambda s, d, n, was=was: read.append(n) or was(s, d, n))
    assert of(spark, sf).count() >= 6 and table in read


def test_sampling_gaps_are_mined_together(spark, sf, monkeypatch):
    from roilens.collect import segment, thin
    from roilens.eval import workloads

    gaps, moves = (10, 40, 60, 100), written(sources.moves(spark, sf, users_per_session=128), "dense")
    want = []
    for eps in gaps:
        kept = written(thin.grid(moves, eps), "kept")
        r = intersect.discover(segment.segment(kept), Params()).collect()
        want.append((eps, kept.count(), len(r), round(sum(x.area for x in r), 3) if r else None))
    calls, was = [], intersect.discover
    monkeypatch.setattr(intersect, "discover", lambda *a: calls.append(a) or was(*a))
    got = workloads.eps_sweep(spark, sf, gaps).select("eps_ms", "kept", "rois", F.round("roi_area", 3))
    assert len(calls) == 1 and rows(got) == sorted(want, key=repr) and any(w[2] for w in want)


def test_distributed_clusters_need_no_broadcast(spark, sf, monkeypatch):
    """Files are small beside the rows they hold, so Spark would send points and their copies through the driver."""
    moves = written(segment.segment(thin.grid(sources.moves(spark, sf, users_per_session=128), 10)), "segmented")
    plans = []
    for module in (cluster, components):
        monkeypatch.setattr(module, "written", lambda df, label: plans.append((label, df)) or written(df, label))
    found = cluster.distributed(moves, Params())
    for label, df in [*plans, ("found", found)]:
        assert "Broadcast" not in df._jdf.queryExecution().sparkPlan().toString(), label
    assert {"pixels", "cores", "cells", "edges", "core-labels"} <= {label for label, _ in plans}
    keep = ("event_id", "cluster_id", "role")
    monkeypatch.undo()
    want = cluster.dbscan(moves, Params(local_cap=10**9)).select(*keep)
    assert rows(found.select(*keep)) == rows(want) and want.where("role = 'core'").count()


@pytest.mark.parametrize("params", [Params(), Params(fuzzy="cmeans"), Params(softmax="state", peculiarity="plain", k=3), Params(update="batch", weights=(0.0, 1.0, 0.0), boundary=True)])
def test_fuzzy_shot_lists_no_match(spark, sf, params, monkeypatch):
    moves, pois = sources.moves(spark, sf), written(facets.carrier(spark, sf).withColumn("brand", F.expr("if(poi_id % 7 = 0, null, brand)")), "pois")
    listed = pipeline.shot(moves, pois, params, None, "fuzzy", listed=True)
    labels = []
    monkeypatch.setattr(pipeline, "written", lambda df, label: labels.append(label) or written(df, label))
    s = pipeline.shot(moves, pois, params, None, "fuzzy")
    assert not {"matched", "scored", "ranked", "facets"} & set(labels)
    six = [F.round(c, 6).alias(c) for c in ("relevance", "membership", "score", "shift")]
    keep = ["session_id", "roi_id", "rank", "poi_id", "k_prime", "iterations", *six, F.round("objective", 4)]
    assert s.highlights.count() and rows(s.highlights.select(*keep)) == rows(listed.highlights.select(*keep))


def test_study_of_approaches_lists_no_match(spark, sf, monkeypatch):
    from roilens.eval import workloads

    def listed(*_):
        raise AssertionError("a row for each match")

    monkeypatch.setattr(fuzzy, "highlight", listed)
    monkeypatch.setattr(relevance, "ranked", lambda df: df.where("raise_error('a row for each match') is null"))
    assert workloads.choose_study(spark, sf).count() == 4


@pytest.mark.parametrize("how", ["topk_mean", "cmeans"])
def test_crowd_refines_as_all_points_do(how):
    import numpy as np

    rng, prm = np.random.default_rng(5), Params(fuzzy=how)
    for z, n, side in ((1, 40, 5), (4, 3000, 12), (6, 900, 60)):
        x, y = rng.integers(-side, side, n), rng.integers(-side, side, n)
        order = np.lexsort([x, y])
        x, y, ids, codes = x[order].astype(float), y[order].astype(float), rng.permutation(n), rng.integers(0, 3, (n, 2))
        inside_, relevances = [], []
        coh, rel, c = np.zeros((z, n)), np.full(n, -np.inf), rng.integers(-side, side, (z, 2)).astype(float)
        for i in range(z):
            at = np.sort(rng.permutation(n)[: n // 2]) if i else np.arange(n)
            inside_.append(at)
            relevances.append(np.round(rng.random(n), 1)[at])
            rel[at] = np.maximum(rel[at], relevances[-1])
            coh[i] = sum((codes[at, a][None, :] == codes[:, a][:, None]).sum(1) for a in range(2)) / (2 * len(at))
        k = rng.integers(0, 6, z)
        by_id = np.argsort(ids)
        want, u, s, it, shift, trace = fuzzy.refine(c, np.column_stack([x, y])[by_id], rel[by_id], coh[:, by_id], k, prm)
        crowd = fuzzy.Crowd(ids, x, y, codes, 3, inside_, relevances)
        got, it2, shift2, trace2 = crowd.refine(c, k, prm)
        assert it == it2 and np.allclose(got, want, atol=1e-9) and np.allclose(trace, trace2)
        chosen, *_ = crowd.highlights(c, k, prm)
        for i in range(z):
            best = np.lexsort([np.arange(n), -np.round(s[i], 9), -np.round(u[i], 9)])[: k[i]]
            assert [b[0] for b in chosen[i]] == best.tolist()
