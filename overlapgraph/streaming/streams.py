"""Streams that keep the coupling map, the costs and the weights up to date.

Each function takes a streaming or a batch frame alike, so batch results are the check of the streams.
Event times must be timestamps (local times are cast on reading), or no watermark is accepted.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.geometry import locate_bucket
from ..operators.meshes import MeshSpec
from ..plans.fixtures import DAY_ZERO
from ..sources.tables import SCHEMAS, shared_dir


def read_events(spark: SparkSession, sf_dir: str, files_per_batch: int | None = None) -> DataFrame:
    """The events table as a file stream; the folder may hold other tables, which the name filter leaves out."""
    reader = spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "*.parquet")
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def locate(events: DataFrame, g: MeshSpec) -> DataFrame:
    """Host element of each event: a stateless projection."""
    day = (F.unix_micros("ts") - F.unix_micros(F.to_timestamp(F.lit(DAY_ZERO)))) / 86_400_000_000
    return locate_bucket(events.withColumn("x", F.array(day)), g).drop("ie_g")


def cell_cost(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Rows and summed values per window and kind; windows that the watermark has passed are final."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    out = events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "total")


def user_sessions(events: DataFrame, gap: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Runs of a user's events as elements."""
    out = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return out.select("user_id", F.col("w.start").alias("start"), "n")


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_parts(events: DataFrame, part: DataFrame, g: MeshSpec) -> DataFrame:
    """Stream-static join: the part that owns each event's host element; the table has one row per element."""
    return locate(events, g).join(part, "e_g")


def view_then_purchase(events: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: a user's purchase within an hour of a view."""
    a = events.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("seen"), F.col("event_id").alias("view_id")).withWatermark("seen", late)
    b = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought"), F.col("event_id").alias("purchase_id")).withWatermark("bought", late)
    on = F.expr(f"u = user_id AND bought >= seen AND bought <= seen + interval {within}")
    return a.join(b, on).select("user_id", "view_id", "purchase_id")


def running_weight(events: DataFrame, g: MeshSpec, late: str = "1 hour") -> DataFrame:
    """Stateful running weight of each host element: (e_g, n, total) after every micro-batch."""

    def step(key: tuple, frames: Iterator, state) -> Iterator:
        import pandas as pd

        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"e_g": [key[0]], "n": [n], "total": [total]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    return locate(events, g).select("e_g", "value").groupBy("e_g").applyInPandasWithState(step, "e_g long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)


def drifted(weights: DataFrame, part: DataFrame, n_dom: int, eps: float = 0.03) -> bool:
    """Whether the heaviest part is beyond its bound, so that a new partition is due."""
    per = weights.join(part, "e_g").groupBy("k").agg(F.sum("total").alias("w"))
    top, total = per.agg(F.max("w"), F.sum("w")).first()
    return bool(total) and top > (1 + eps) * total / n_dom


def run_to_table(stream: DataFrame, name: str, mode: str = "append", each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Run a stream over all that is there; the sink's rows as a batch frame.

    Append results go to Parquet; update results overwrite one folder per micro-batch, so repeats after a
    failure leave no trace, and the last value per batch can be taken by its ``batch`` column.
    """
    import uuid

    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True)
    if mode == "append":
        writer = writer.format("parquet").option("path", f"{base}/out")
    else:

        def put(batch: DataFrame, i: int) -> None:
            batch.write.mode("overwrite").parquet(f"{base}/out/batch={i}")
            if each:
                each(batch, i)

        writer = writer.foreachBatch(put)
    writer.start().awaitTermination()
    from pyspark.sql.types import LongType, StructField, StructType

    extra = [] if mode == "append" else [StructField("batch", LongType())]
    return spark.read.schema(StructType([*stream.schema.fields, *extra])).parquet(f"{base}/out")
