"""A point quadtree as tables: leaves by level-wise counts, membership by cell code, covers by a join.

Coordinates are integers in [0, 2**depth); a cell at depth d is the leading d bits of both.  A leaf is
the shallowest cell with at most ``capacity`` points (or max_depth); empty cells are not stored.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import polygon


@dataclass(frozen=True)
class Root:
    """The root square: lower corner, side in map units, and bits of depth."""

    x0: float = -1024.0
    y0: float = -1024.0
    side: float = 2048.0
    bits: int = 11

    @classmethod
    def around(cls, pois: DataFrame, x: str = "mx", y: str = "my") -> Root:
        """The default square, doubled about its centre until it holds all points; finest cells keep their size."""
        r = pois.agg(F.min(x).alias("x0"), F.max(x).alias("x1"), F.min(y).alias("y0"), F.max(y).alias("y1")).first()
        root = cls()
        while r.x0 is not None and (min(r.x0, r.y0) < root.x0 or max(r.x1, r.y1) >= root.x0 + root.side):
            root = cls(2 * root.x0, 2 * root.y0, 2 * root.side, root.bits + 1)
            if root.bits > 31:
                raise ValueError("points lie too far out for a code of 62 bits")
        return root

    def cell(self, v: Column, origin: float) -> Column:
        scale = 2**self.bits / self.side
        return F.least(F.greatest(F.floor((v - F.lit(origin)) * F.lit(scale)), F.lit(0)), F.lit(2**self.bits - 1)).cast("long")


def morton(cx: Column, cy: Column, bits: int) -> Column:
    """Bits of both coordinates interleaved."""
    parts = [F.shiftleft(F.shiftright(cx, i).bitwiseAND(F.lit(1).cast("long")), 2 * i).bitwiseOR(F.shiftleft(F.shiftright(cy, i).bitwiseAND(F.lit(1).cast("long")), 2 * i + 1)) for i in range(bits)]
    return reduce(lambda a, b: a.bitwiseOR(b), parts)


def coded(pois: DataFrame, root: Root = Root(), x: str = "mx", y: str = "my") -> DataFrame:
    """pois with the Morton ``code`` of their finest cell."""
    return pois.withColumn("code", morton(root.cell(F.col(x), root.x0), root.cell(F.col(y), root.y0), root.bits))


def build(pois: DataFrame, capacity: int = 64, max_depth: int = 11, root: Root = Root(), x: str = "mx", y: str = "my") -> DataFrame:
    """(depth, code, n, x0, y0, size): the leaves.

    Points are counted once per finest cell; every level's counts come from that table, which the
    grid bounds, not from the points.
    """
    depth = min(max_depth, root.bits)
    cells = coded(pois, root, x, y).groupBy("code").agg(F.count("*").alias("n"))
    # one row per level and cell in one pass: a finest cell counts for all its ancestors
    levels = cells.select("n", F.col("code").alias("_fine"), F.explode(F.sequence(F.lit(0), F.lit(depth))).alias("depth"))
    counts = levels.withColumn("code", F.expr(f"shiftright(_fine, cast(2 * ({root.bits} - depth) as int))")).groupBy("depth", "code").agg(F.sum("n").alias("n"))
    parent = counts.select((F.col("depth") + 1).alias("_d"), F.col("code").alias("_c"), F.col("n").alias("_up"))
    joined = counts.join(parent, (F.col("depth") == F.col("_d")) & (F.expr("shiftright(code, 2)") == F.col("_c")), "left")
    leaf = joined.where(((F.col("n") <= capacity) | (F.col("depth") == depth)) & ((F.col("depth") == 0) | (F.col("_up") > capacity)))
    return with_box(leaf.select("depth", "code", "n"), root)


def with_box(cells: DataFrame, root: Root = Root()) -> DataFrame:
    """Cells with their lower corner (x0, y0) and side length ``size`` in map units."""
    cx = reduce(lambda a, b: a.bitwiseOR(b), [F.shiftleft(F.shiftright("code", 2 * i).bitwiseAND(F.lit(1).cast("long")), i) for i in range(root.bits)])
    cy = reduce(lambda a, b: a.bitwiseOR(b), [F.shiftleft(F.shiftright("code", 2 * i + 1).bitwiseAND(F.lit(1).cast("long")), i) for i in range(root.bits)])
    size = F.lit(root.side) / F.pow(F.lit(2.0), F.col("depth"))
    out = cells.withColumn("size", size)
    return out.withColumn("x0", F.lit(root.x0) + cx * F.col("size")).withColumn("y0", F.lit(root.y0) + cy * F.col("size"))


def member(pois: DataFrame, leaves: DataFrame, root: Root = Root(), x: str = "mx", y: str = "my") -> DataFrame:
    """pois with the (depth, code) of their leaf: an equi-join on the prefixes of its code, one a level."""
    p = coded(pois, root, x, y).withColumnRenamed("code", "_fine")
    up = p.select("*", F.explode(F.sequence(F.lit(0), F.lit(root.bits))).alias("_d")).withColumn("_c", F.expr(f"shiftright(_fine, cast(2 * ({root.bits} - _d) as int))"))
    key = leaves.select(F.col("depth").alias("depth"), F.col("code").alias("code"))
    return up.join(key, (F.col("_d") == F.col("depth")) & (F.col("_c") == F.col("code"))).drop("_d", "_c", "_fine")


def cover(rois: DataFrame, leaves: DataFrame, poly: str = "poly", root: Root = Root()) -> DataFrame:
    """(session_id, roi_id, depth, code, inside): leaves that meet a polygon's interior or edge.

    The bounding boxes decide first; ``inside`` (all corners strictly within) lets a match skip the
    exact test.
    """
    box = rois.withColumn("_b", polygon.bbox(F.col(poly)))
    square = F.array(
        *(F.struct((F.col("x0") + F.lit(dx) * F.col("size")).alias("x"), (F.col("y0") + F.lit(dy) * F.col("size")).alias("y")) for dx, dy in ((0.0, 0.0), (1.0, 0.0), (1.0, 1.0), (0.0, 1.0)))
    )
    near = (F.col("x0") <= F.col("_b.x1")) & (F.col("x0") + F.col("size") >= F.col("_b.x0")) & (F.col("y0") <= F.col("_b.y1")) & (F.col("y0") + F.col("size") >= F.col("_b.y0"))
    keys = ["_deep", "_d", "_c"]
    met = _box_cells(box, root).join(_leaf_cells(leaves), keys).where(near).withColumn("_sq", square)
    met = met.where(~polygon.apart(F.col(poly), F.col("_sq")))
    inside = F.forall("_sq", lambda v: polygon.contains(F.col(poly), v["x"], v["y"]))
    return met.select("session_id", "roi_id", "depth", "code", inside.alias("inside"))


def _shifted(code: str, levels: str) -> Column:
    return F.expr(f"shiftright({code}, cast(2 * ({levels}) as int))")


def _box_cells(box: DataFrame, root: Root) -> DataFrame:
    """Boxes dealt to cell codes (_deep, _d, _c) as fine as the boxes are small.

    A box touches at most three by three cells of the level whose cells are no smaller than it.  For
    leaves at that level or above it has those cells' ancestors, each once; for deeper ones the cells.
    """
    span = F.greatest(F.col("_b.x1") - F.col("_b.x0"), F.col("_b.y1") - F.col("_b.y0"), F.lit(root.side / 2**root.bits))
    out = box.withColumn("_l", F.greatest(F.least(F.floor(F.log2(F.lit(root.side) / span)), F.lit(root.bits)), F.lit(0)).cast("int"))
    scale = F.pow(F.lit(2.0), F.col("_l")) / F.lit(root.side)
    top = F.expr("shiftleft(1L, _l) - 1")

    def within(c: Column) -> Column:
        return F.least(F.greatest(c.cast("long"), F.lit(0).cast("long")), top)

    for axis, low in (("x", root.x0), ("y", root.y0)):
        first = within(F.ceil((F.col(f"_b.{axis}0") - F.lit(low)) * scale) - 1)
        last = within(F.floor((F.col(f"_b.{axis}1") - F.lit(low)) * scale))
        out = out.withColumn(f"_f{axis}", first).withColumn(f"_c{axis}", F.explode(F.sequence(first, F.greatest(first, last))))
    out = out.withColumn("_i", F.explode(F.sequence(F.lit(0), F.col("_l") + 1))).withColumn("_d", F.least("_i", "_l")).withColumn("_deep", F.col("_i") > F.col("_l"))
    for axis in "xy":  # of cells with one ancestor the first stands for it
        out = out.where(F.col(f"_c{axis}") == F.greatest(F.col(f"_f{axis}"), F.expr(f"shiftleft(shiftright(_c{axis}, _l - _d), _l - _d)")))
    out = out.withColumn("_own", morton(F.col("_cx"), F.col("_cy"), root.bits)).withColumn("_c", _shifted("_own", "_l - _d"))
    return out.select(*box.columns, "_deep", "_d", "_c")


def _leaf_cells(leaves: DataFrame) -> DataFrame:
    """Leaves under their own code and, as deeper ones, under all their ancestors'."""
    up = leaves.withColumn("_d", F.explode(F.sequence(F.lit(0), F.col("depth").cast("int"))))
    return up.withColumn("_deep", F.col("_d") < F.col("depth")).withColumn("_c", _shifted("code", "depth - _d"))


def save(pois: DataFrame, leaves: DataFrame, path: str, root: Root = Root(), prefix_depth: int = 3) -> None:
    """Write leaves and coded points, points partitioned by a code prefix and sorted by code for min/max skipping."""
    leaves.write.mode("overwrite").parquet(f"{path}/leaves")
    m = member(pois, leaves, root).withColumn("prefix", F.expr(f"cast(shiftright(code, cast(greatest(0, 2 * (depth - {prefix_depth})) as int)) as int)"))
    m.repartition("prefix").sortWithinPartitions("prefix", "depth", "code").write.mode("overwrite").partitionBy("prefix").parquet(f"{path}/points")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(points with depth and code, leaves) as written by ``save``."""
    return spark.read.parquet(f"{path}/points"), spark.read.parquet(f"{path}/leaves")


def append(old: DataFrame, new: DataFrame, capacity: int = 64, max_depth: int = 11, root: Root = Root()) -> DataFrame:
    """Leaves after more points came: only the finest counts of both are added up."""
    return build(old.select("mx", "my").unionByName(new.select("mx", "my")), capacity, max_depth, root)
