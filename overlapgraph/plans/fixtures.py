"""Carriers of the data model: generated grids, and meshes made of the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import geometry
from ..operators.meshes import MESH_STRIDE, MeshSpec, box_pair, incidence, incidence_mesh
from ..sources.tables import load

#: The time axis starts here (fixed value); one span is a day.
DAY_ZERO = "2024-01-01 00:00:00"
DAYS = 30


def grid(n: int = 5, p: int = 3, m: int = 4, side: float = 0.4) -> tuple[MeshSpec, MeshSpec]:
    return box_pair(n, p, m, side)


def time_pair() -> tuple[MeshSpec, MeshSpec]:
    """Thirty daily cubic spans, and twelve linear elements of six hours on the first three days."""
    return MeshSpec("G", "spline", 3, (DAYS,), (0.0,), (float(DAYS),), 0), MeshSpec("L", "lagrange", 1, (12,), (0.0,), (3.0,), 1)


def cube_pair() -> tuple[MeshSpec, MeshSpec]:
    """Five cubic spans per axis for sales rows, and a linear mesh on the first two of them."""
    return box_pair(5, 3, 4, 0.4)


def event_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as points of the time axis, in days: (x, w, value, event_id, event_type)."""
    day = (F.unix_micros("ts") - F.unix_micros(F.to_timestamp(F.lit(DAY_ZERO)))) / 86_400_000_000
    return load(spark, sf_dir, "events").select(F.array(day).alias("x"), F.lit(1.0).alias("w"), "value", "event_id", "event_type")


def sale_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sales rows as points of the unit cube: (x, w, price)."""
    x = F.array((F.col("l_quantity") - 1) / 49, F.col("l_discount") / 0.1, F.col("l_tax") / 0.08)
    return load(spark, sf_dir, "lineitem").select(x.alias("x"), F.lit(1.0).alias("w"), F.col("l_extendedprice").alias("price"), "l_orderkey", "l_linenumber")


def sales_inside(spark: SparkSession, sf_dir: str, local: MeshSpec) -> DataFrame:
    """Sales rows of a local box with their element ``e`` there; the box is half open at its outer faces, as spans are."""
    x, tol = F.col("x"), geometry.TOLERANCE
    inside = [F.floor((x[a] - local.lo[a]) / local.h[a] + tol) < local.n_el[a] for a in range(local.dim)]
    pts = sale_points(spark, sf_dir).where(inside[0] & inside[1] & inside[2])
    return geometry.locate_bucket(pts, local).withColumnRenamed("e_g", "e").drop("ie_g")


def sold(spark: SparkSession, sf_dir: str, g: MeshSpec, local: MeshSpec) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The pair of meshes as sales rows fill it: elements (e, n) with rows in them, globally and locally, and cells (e_l, e_g, n_q)."""
    in_g = geometry.locate_bucket(sale_points(spark, sf_dir), g).groupBy(F.col("e_g").alias("e")).agg(F.count(F.lit(1)).alias("n"))
    cells = geometry.crossed_elements(geometry.coupling_map(sales_inside(spark, sf_dir, local), g))
    return in_g, cells.groupBy(F.col("e_l").alias("e")).agg(F.sum("n_q").alias("n")), cells


def sold_incidence(spark: SparkSession, spec: MeshSpec, filled: DataFrame) -> DataFrame:
    """Rows (e, v) of the elements that hold rows."""
    return incidence(spark, spec).join(F.broadcast(filled.select("e")), "e", "left_semi").select("e", "v")


def orders_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Global incidence: an order is an element, its parts are the vertices."""
    return incidence_mesh(load(spark, sf_dir, "lineitem"), F.col("l_orderkey"), F.col("l_partkey"), "G")


def _region_orders(spark: SparkSession, sf_dir: str, region: int) -> DataFrame:
    nation = load(spark, sf_dir, "nation").where(F.col("n_regionkey") == region)
    cust = load(spark, sf_dir, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"), "left_semi")
    return load(spark, sf_dir, "orders").join(cust, F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("o_orderkey", "o_custkey")


def customers_suppliers(spark: SparkSession, sf_dir: str, region: int = 0) -> DataFrame:
    """Local incidence: a customer of one region is an element, the suppliers of their lines are the vertices."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    both = _region_orders(spark, sf_dir, region).join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    return incidence_mesh(both, F.col("o_custkey"), F.col("l_suppkey") + MESH_STRIDE, "L")


def customer_orders(spark: SparkSession, sf_dir: str, region: int = 0) -> DataFrame:
    """Cells (e_l, e_g): each such customer with each of their orders that has lines."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey").distinct()
    return _region_orders(spark, sf_dir, region).join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select(F.col("o_custkey").alias("e_l"), F.col("o_orderkey").alias("e_g")).distinct()


def document_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Incidence (e, v): a document holds a line; blank lines and null texts take no part."""
    line = F.explode(F.split("text", "\n")).alias("line")
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("v"), line).select(F.trim("line").alias("e"), "v").where("e <> ''").distinct()


def shingles(df: DataFrame, key: str, text: str = "text", width: int = 8) -> DataFrame:
    """Rows (key, s): the runs of ``width`` words of each text, lower case; the words are split once per row."""
    words = df.select(key, F.split(F.trim(F.regexp_replace(F.lower(text), r"\s+", " ")), " ").alias("w")).where(F.size("w") >= width)
    runs = F.transform(F.sequence(F.lit(1), F.size("w") - width + 1), lambda i: F.array_join(F.slice("w", i, width), " "))
    return words.select(key, F.explode(runs).alias("s"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Incidence (e, v): a page names a link target."""
    got = F.explode(F.regexp_extract_all("html", F.lit("href=.([^\"' >]+)"), 1)).alias("e")
    return load(spark, sf_dir, "pages").select(got, F.col("page_id").alias("v")).distinct()
