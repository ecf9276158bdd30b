"""POI sets and their facets: any table with a place and attributes of finite domains.

The facet dictionary keeps attribute and value as text, so that what has been learnt stays readable.
Numeric attributes are binned first.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..collect.sources import ANCHOR_X, ANCHOR_Y, at_index
from ..geo.projection import to_map
from ..storage import table


@dataclass(frozen=True)
class PoiSchema:
    """Which column is the id, and how each attribute is got (a column or SQL expression by name)."""

    id: str
    attrs: dict[str, str] = field(default_factory=dict)
    binners: dict[str, tuple[float, float, int]] = field(default_factory=dict)


def equal_width(value: Column, low: float, high: float, bins: int) -> Column:
    """Number of the equal-width bin a value falls in, as text; outliers go to the end bins."""
    step = (high - low) / bins
    return F.least(F.greatest(F.floor((value - low) / step), F.lit(0)), F.lit(bins - 1)).cast("string")


def edges_bin(value: Column, edges: list[float]) -> Column:
    """Number of the first explicit edge above a value, as text."""
    out = F.lit(str(len(edges)))
    for i in range(len(edges) - 1, -1, -1):
        out = F.when(value < edges[i], str(i)).otherwise(out)
    return out


def ntile_bin(df: DataFrame, column: str, name: str, bins: int) -> DataFrame:
    """Bins of equal counts by approximate quantiles, which need no global sort."""
    cuts = df.agg(F.percentile_approx(column, [i / bins for i in range(1, bins)], 10000).alias("c")).first().c or []
    return df.withColumn(name, edges_bin(F.col(column), sorted(set(map(float, cuts)))))


def place(key: Column) -> tuple[Column, Column]:
    """Carrier P's pixel (mx, my) of an integer key: five hot spots and a scatter over the viewport."""
    c = key % 8
    x = F.when(c < 5, at_index(ANCHOR_X, c) + (key * 48271) % 121 - 60).otherwise((key * 48271) % 1601 - 800)
    y = F.when(c < 5, at_index(ANCHOR_Y, c) + (key * 16807) % 113 - 56).otherwise((key * 16807) % 901 - 450)
    return x.cast("long").alias("mx"), y.cast("long").alias("my")


def pois(df: DataFrame, schema: PoiSchema) -> DataFrame:
    """(poi_id, mx, my, lat, lon, attributes...) of any table, placed by carrier P's formulas."""
    key = F.col(schema.id).cast("long")
    base = df.withColumn("poi_id", key)
    mx, my = place(F.col("poi_id"))
    base = base.withColumn("mx", mx).withColumn("my", my)
    lat, lon = to_map(F.col("mx").cast("double"), F.col("my").cast("double"))
    attrs = [F.expr(e).cast("string").alias(a) for a, e in schema.attrs.items()]
    binned = [equal_width(F.col(c), *how).alias(f"{c}_bin") for c, how in schema.binners.items()]
    return base.select("poi_id", "mx", "my", lat, lon, *attrs, *binned)


# The carriers' schemas.
CARRIERS: dict[str, tuple[str, PoiSchema]] = {
    "part": ("part", PoiSchema("p_partkey", {"brand": "p_brand", "type": "p_type", "size_decade": "(p_size - 1) div 10", "colour": "split_part(p_name, ' ', 1)", "noun": "split_part(p_name, ' ', 2)"})),
    "documents": ("documents", PoiSchema("doc_id", {"lang": "lang", "source": "source", "length": "least(9, n_chars div 1000)"})),
    "customer": ("customer", PoiSchema("c_custkey", {"segment": "c_mktsegment", "nation": "c_nationkey"}, {"c_acctbal": (-1000.0, 10000.0, 10)})),
    "supplier": ("supplier", PoiSchema("s_suppkey", {"nation": "s_nationkey"}, {"s_acctbal": (-1000.0, 10000.0, 10)})),
    "benchmark": ("benchmark", PoiSchema("item_id", {"length": "length(text) div 50"})),
    "pages": ("pages", PoiSchema("page_id", {"host": "split_part(split_part(url, '//', 2), '/', 1)"})),
    "orders": ("orders", PoiSchema("o_orderkey", {"status": "o_orderstatus", "priority": "o_orderpriority"})),
    "embeddings": ("embeddings", PoiSchema("vec_id", {"label": "label"})),
    "lineitem": ("lineitem", PoiSchema("key", {"returnflag": "l_returnflag", "linestatus": "l_linestatus", "discount": "cast(round(l_discount * 100) as int)", "tax": "cast(round(l_tax * 100) as int)", "quantity": "cast((l_quantity - 1) / 10 as int)"})),
}


def carrier(spark: SparkSession, sf_dir: str, name: str = "part") -> DataFrame:
    """A named carrier as POIs."""
    of, schema = CARRIERS[name]
    df = table(spark, sf_dir, of)
    if name == "lineitem":
        df = df.withColumn("key", F.col("l_orderkey") * 8 + F.col("l_linenumber"))
    out = pois(df, schema)
    if name == "embeddings":
        e = df.select(F.col("vec_id").cast("long").alias("poi_id"), F.round(F.element_at("embedding", 1) * 1000).cast("long").alias("mx"), F.round(F.element_at("embedding", 2) * 1000).cast("long").alias("my"))
        out = out.drop("mx", "my").join(e, "poi_id")
    return out


def attributes(pois_: DataFrame) -> list[str]:
    return [c for c in pois_.columns if c not in ("poi_id", "mx", "my", "lat", "lon", "code", "depth", "prefix", "inside")]


def facets(pois_: DataFrame) -> DataFrame:
    """(poi_id, attr, val): one row for each attribute that has a value."""
    names = attributes(pois_)
    pairs = F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("val")) for a in names))
    return pois_.select("poi_id", F.inline(pairs)).where("val is not null")


def from_map(df: DataFrame, id_: str = "poi_id", attrs: str = "attrs") -> DataFrame:
    """Facets of a schema-free catalogue whose attributes are a map."""
    return df.select(F.col(id_).alias("poi_id"), F.explode(attrs).alias("attr", "val"))


def dictionary(facets_: DataFrame) -> DataFrame:
    """(attr, val, cell_id): all cells; its rows are bounded by the attributes' domains."""
    return facets_.select("attr", "val").distinct().withColumn("cell_id", F.row_number().over(W.orderBy("attr", "val")))


def roi_vector(matched: DataFrame, facets_: DataFrame) -> DataFrame:
    """(session_id, roi_id, attr, val): cells that some matching point of a region has."""
    return matched.join(facets_, "poi_id").select("session_id", "roi_id", "attr", "val").distinct()


def vector_of(counts: DataFrame) -> DataFrame:
    """``roi_vector`` from the number of a region's points by facet (``inside.counts``)."""
    return counts.where("attr is not null").select("session_id", "roi_id", "attr", "val")
