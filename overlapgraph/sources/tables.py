"""Reading the given tables with fixed schemas, and writing and reading the engine's own stores."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Tables and columns as they are given (fixed schemas).
SCHEMAS = {
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}

_own_dir: list[str] = []


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table: fixed schema, negative zeros made plain, local times as UTC timestamps."""
    df = spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")
    fixed = {}
    for f in df.schema:
        kind = f.dataType.simpleString()
        if f.name in ("l_discount", "l_tax"):
            fixed[f.name] = F.col(f.name) + 0.0
        elif kind == "timestamp_ntz":
            fixed[f.name] = F.col(f.name).cast("timestamp")
    return df.withColumns(fixed) if fixed else df


def register_views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(SCHEMAS)) -> None:
    for n in names:
        load(spark, sf_dir, n).createOrReplaceTempView(n)


def shared_dir(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; one of our own only where the session names none."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not _own_dir:
        _own_dir.append("file://" + tempfile.mkdtemp(prefix="overlapgraph-"))
    return _own_dir[0]


def store(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage through a table in the shared folder; iterative methods call it every round."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def save_geometry(db: DataFrame, path: str, mesh: str) -> None:
    """The geometric database of a mesh, sorted by element, so that a part reads its own row groups."""
    db.withColumn("mesh", F.lit(mesh)).repartitionByRange("e").sortWithinPartitions("e", "q").write.mode("overwrite").partitionBy("mesh").parquet(path)


def load_geometry(spark: SparkSession, path: str, mesh: str) -> DataFrame:
    return spark.read.parquet(path).where(F.col("mesh") == mesh)


def save_parts(df: DataFrame, path: str) -> None:
    """One folder per part; a reader of one part opens that folder alone."""
    df.repartition("k").write.mode("overwrite").partitionBy("k").parquet(path)


def load_part(spark: SparkSession, path: str, k: int) -> DataFrame:
    return spark.read.parquet(path).where(F.col("k") == k)


def write_coo(entries: DataFrame, path: str, form: str = "csv") -> None:
    """Matrix entries (i, j, val) as csv, json, orc or parquet."""
    writer = entries.select("i", "j", "val").write.mode("overwrite")
    getattr(writer, form)(path)


def read_coo(spark: SparkSession, path: str, form: str = "csv") -> DataFrame:
    return getattr(spark.read.schema("i bigint, j bigint, val double"), form)(path)


def write_solution(points: DataFrame, path: str) -> None:
    points.write.mode("overwrite").parquet(path)


def small(df: DataFrame, max_rows: int = 200_000) -> DataFrame:
    """Broadcast after its number of rows was checked; a shuffle join serves beyond the bound."""
    return F.broadcast(df) if df.select(F.lit(1)).limit(max_rows + 1).count() <= max_rows else df
