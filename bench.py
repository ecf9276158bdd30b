"""Times the headline queries; prints one JSON line.  BENCH_SF_DIR and BENCH_CPUS choose data and cores."""

from __future__ import annotations

import json
import os
import tempfile
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

from pyspark.sql import SparkSession  # noqa: E402

from roilens import queries  # noqa: E402

HEADLINE = (
    "single_shot", "q_thin_grid", "q_seg_fixed", "q_seg_drift_tiered", "q_dbscan_clusters", "q_dbscan_distributed", "q_hull_area", "q_roi_area",
    "q_quadtree_leaves", "q_match", "q_feedback_sequential", "q_relevance", "q_fuzzy_topk", "q_click_only", "q_index_scale", "q_eps_sweep",
)


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .config("spark.checkpoint.dir", "file://" + tempfile.mkdtemp(prefix="roilens-bench-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    known = queries.queries()
    spark.range(10).count()
    took = {}
    for name in HEADLINE:
        t = time.monotonic()
        known[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.monotonic() - t, 3)
    print(json.dumps({"metric": "headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    main()
