"""Queries that run the streams and the function surface, against their batch twins in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sqlfuncs
from ..sources import gridmesh
from ..sources.tables import load
from ..streaming import streams
from . import fixtures
from .catalog_grid import _r, sql_splines

QUERIES: dict = {}
SQL: dict[str, str] = {}
_DAY = "(epoch_us(ts::TIMESTAMP) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) / 86400000000.0::DOUBLE"


def query(sql: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return put


def _run(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    return streams.run_to_table(stream, name, mode)


@query(f"SELECT event_id, CAST(least(greatest(floor({_DAY} + 1e-8), 0), 29) AS BIGINT) AS e_g FROM events")
def stream_locate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _run(streams.locate(streams.read_events(spark, sf_dir), fixtures.time_pair()[0]).select("event_id", "e_g"), "locate")


_WINDOWED = "WITH m AS (SELECT max(epoch_us(ts::TIMESTAMP)) - 3600000000 AS mark FROM events), "


@query(_WINDOWED + "d AS (SELECT epoch_us(ts::TIMESTAMP) // 86400000000 AS day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL) SELECT day, event_type, n, total FROM d, m WHERE (day + 1) * 86400000000 <= mark")
def stream_cell_cost_tumbling(spark, sf_dir):
    """Daily sums; the days that the watermark has passed."""
    out = _run(streams.cell_cost(streams.read_events(spark, sf_dir)), "tumbling")
    return out.select(F.expr("unix_micros(start) div 86400000000").alias("day"), "event_type", "n", _r("total", 4).alias("total"))


@query(
    _WINDOWED + "s AS (SELECT (epoch_us(ts::TIMESTAMP) // 21600000000 - o) AS slot, event_type, count(*) AS n FROM events, (SELECT range AS o FROM range(4)) GROUP BY ALL) "
    "SELECT slot, event_type, n FROM s, m WHERE (slot + 4) * 21600000000 <= mark"
)
def stream_cell_cost_sliding(spark, sf_dir):
    out = _run(streams.cell_cost(streams.read_events(spark, sf_dir), "1 day", "6 hours"), "sliding")
    return out.select(F.expr("unix_micros(start) div 21600000000").alias("slot"), "event_type", "n")


@query(
    _WINDOWED + "e AS (SELECT user_id, epoch_us(ts::TIMESTAMP) AS t, event_id FROM events), g AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t, event_id) < 3600000000 THEN 0 ELSE 1 END AS fresh FROM e), "
    "s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY t, event_id ROWS UNBOUNDED PRECEDING) AS sid FROM g), r AS (SELECT user_id, sid, min(t) AS t0, max(t) + 3600000000 AS t1, count(*) AS n FROM s GROUP BY ALL) "
    "SELECT user_id, t0 AS start_us, n FROM r, m WHERE t1 <= mark"
)
def stream_user_sessions(spark, sf_dir):
    return _run(streams.user_sessions(streams.read_events(spark, sf_dir)), "sessions").select("user_id", F.unix_micros("start").alias("start_us"), "n")


@query("SELECT DISTINCT event_id FROM events")
def stream_dedup(spark, sf_dir):
    return _run(streams.without_repeats(streams.read_events(spark, sf_dir)).select("event_id"), "dedup")


@query(f"SELECT CAST(least(greatest(floor({_DAY} + 1e-8), 0), 29) AS BIGINT) AS e_g, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def stream_running_weight(spark, sf_dir):
    """Weights kept by state; the last value of each element."""
    out = _run(streams.running_weight(streams.read_events(spark, sf_dir), fixtures.time_pair()[0]), "running", "update")
    last = out.groupBy("e_g").agg(F.max_by(F.struct("n", "total"), "batch").alias("s"))
    return last.select("e_g", "s.n", _r("s.total", 4).alias("total"))


@query(f"SELECT CAST(least(greatest(floor({_DAY} + 1e-8), 0), 29) % 4 AS INT) AS k, count(*) AS n FROM events GROUP BY ALL")
def stream_part_join(spark, sf_dir):
    part = spark.range(30).select(F.col("id").alias("e_g"), (F.col("id") % 4).cast("int").alias("k"))
    out = _run(streams.with_parts(streams.read_events(spark, sf_dir), F.broadcast(part), fixtures.time_pair()[0]).select("event_id", "k"), "parts")
    return out.groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT a.user_id, a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def stream_view_purchase(spark, sf_dir):
    return _run(streams.view_then_purchase(streams.read_events(spark, sf_dir)), "pairs")


# ---- functions and the data source -----------------------------------------------------------------


@query(f"WITH p AS (SELECT event_id AS pt, CAST(least(greatest(floor({_DAY} + 1e-8), 0), 29) AS BIGINT) AS s, {_DAY} AS x FROM events), {sql_splines(30, 3, 'p', 'b', 0.0, 1.0)} SELECT pt AS event_id, CAST(i - s AS INT) AS a, round(n, 7) + 0.0 AS val FROM b")
def udf_spline_values(spark, sf_dir):
    sqlfuncs.register(spark)
    fixtures.event_points(spark, sf_dir).selectExpr("event_id", "x[0] / 30 AS x").createOrReplaceTempView("og_points")
    return spark.sql("SELECT event_id, pos AS a, round(val, 7) + 0.0D AS val FROM (SELECT event_id, posexplode(og_spline_values(x, 30, 3)) AS (pos, val) FROM og_points)")


@query("SELECT event_type, round(sqrt(sum(pow(value - 50, 2))), 5) AS norm FROM events GROUP BY event_type")
def udaf_weighted_l2(spark, sf_dir):
    e = load(spark, sf_dir, "events").select("event_type", "value", F.lit(50.0).alias("m"), F.lit(1.0).alias("w"))
    return e.groupBy("event_type").agg(_r(sqlfuncs.weighted_l2("value", "m", "w"), 5).alias("norm"))


@query("SELECT DISTINCT a.l_partkey AS i, b.l_partkey AS j FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <= b.l_partkey")
def udtf_support_pairs(spark, sf_dir):
    """Pairs of an order's parts by a table function; an order is small, a large element takes the chunked join."""
    sqlfuncs.register(spark)
    fixtures.orders_parts(spark, sf_dir).groupBy("e").agg(F.collect_set("v").alias("vs")).createOrReplaceTempView("og_elements")
    return spark.sql("SELECT DISTINCT p.i, p.j FROM og_elements e, LATERAL og_support_pairs(e.vs) p")


@query("SELECT a.range AS i, CAST(b.range AS INT) AS j FROM range(40) a, range(40) b WHERE abs(a.range - b.range) <= 3")
def udtf_neighbour_band(spark, sf_dir):
    sqlfuncs.register(spark)
    spark.range(40).createOrReplaceTempView("og_axis")
    return spark.sql("SELECT a.id AS i, b.j FROM og_axis a, LATERAL og_neighbour_band(CAST(a.id AS INT), 3, 40) b")


@query("SELECT range AS v, CAST(range % 6 AS INT) AS i0, CAST(range // 6 % 6 AS INT) AS i1, CAST(range // 36 AS INT) AS i2 FROM range(216)")
def ds_gridmesh(spark, sf_dir):
    gridmesh.register(spark)
    m = spark.read.format("gridmesh").option("n", 4).option("degree", 2).option("dim", 3).load()
    return m.select("v", *[F.col("ix")[k].alias(f"i{k}") for k in range(3)])
