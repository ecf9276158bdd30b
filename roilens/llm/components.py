"""Connected components of a graph too large for one machine.

Alternating star contraction: every vertex hands its larger (then its smaller) neighbours to the
smallest vertex it knows.  Each round is two grouped minima and two equi-joins; after a number of
rounds logarithmic in the component size every edge points at its component's smallest vertex.  Each
round is written to the shared folder, so a lost executor costs a round's tasks at most.  Minima
combine on the map side and joins may be split by adaptive execution, so a hub vertex is no hot spot.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

MAX_ROUNDS = 60


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy(F.col("a").alias("u")).agg(F.min("b").alias("m")).select("u", F.least("u", "m").alias("m"))
    up = both.where("b > a").join(least, F.col("a") == F.col("u"))
    return up.select(F.col("m").alias("a"), "b").where("a < b").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    least = edges.groupBy(F.col("b").alias("u")).agg(F.min("a").alias("m"))
    down = edges.join(least, F.col("b") == F.col("u")).where("a > m").select(F.col("m").alias("a"), F.col("a").alias("b"))
    return down.unionAll(least.select(F.col("m").alias("a"), F.col("u").alias("b"))).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every vertex of ``edges`` (a, b); root is the least vertex of its component.

    Loops and doubled edges are harmless; vertices without an edge do not appear.
    """
    edges = written(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), "edges")
    mark = None
    for _ in range(MAX_ROUNDS):
        edges = written(_small_star(_large_star(edges)), "edges")
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError(f"components did not settle in {MAX_ROUNDS} rounds")
    roots = edges.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct()
    return edges.select(F.col("b").alias("node"), F.col("a").alias("root")).unionAll(roots)
