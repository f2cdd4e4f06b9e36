"""Exact duplicates by a stateful stream with disk-backed keyed state that never expires.

A first pass writes the arrival log: id, digest of the normalised text, and the locator (file and
row) of its content. The stream over that log keeps, for each digest, the smallest id
with its locator and the number of arrivals, in RocksDB state without watermark. Spark
aggregates inside each task before the state's shuffle, so a digest that a third of all rows share
costs one row per task. A digest hit is a claim, not a proof: every hit's full text is
then compared with the retained text, found by its locator, and texts that differ are grouped anew.

With a ``state_dir`` log, checkpoint and state stay on disk: documents that arrive in a later run, or after a
restart, are deduplicated against all earlier ones.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import FILE, ROW, bounded_broadcast, drop_scratch, field, join_groups, located, materialise, scratch_mark, scratch_path, squeezed, unpacked

#: Up to this many digests (about 60 bytes each) are broadcast; beyond it the joins shuffle.
BROADCAST_ROWS = 300_000
#: Copies of one text are compared in groups of about this many.
HITS_PER_SALT = 64

_ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
_CONF = {
    "spark.sql.streaming.stateStore.providerClass": _ROCKS,
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "128",
    # many small stores: no space is reserved ahead, and a commit uploads changes, not snapshots
    "spark.sql.streaming.stateStore.rocksdb.allowFAllocate": "false",
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
}


def sha256_digest(text: Column) -> Column:
    return F.sha2(text.cast("binary"), 256)


def retain(log: DataFrame, root: str, files_per_batch: int | None = None) -> DataFrame:
    """Run the stream over the arrival logs below ``root`` until it has all of them; the changed state as rows.

    Rows: digest, keep (struct that starts with the smallest id and holds its locator), n. The
    sink overwrites one folder per micro-batch, so a batch that is run again after a failure leaves no trace;
    checkpoint and sink lie beside the logs, so a later call goes on where this one ended.
    """
    spark = log.sparkSession
    out = f"{root}/told"
    before = {k: spark.conf.get(k, None) for k in _CONF}
    for k, v in _CONF.items():
        spark.conf.set(k, v)
    try:
        source = spark.readStream.schema(log.schema).option("recursiveFileLookup", "true")
        if files_per_batch:
            source = source.option("maxFilesPerTrigger", files_per_batch)
        state = source.parquet(f"{root}/log").groupBy("digest").agg(F.min("at").alias("keep"), F.count(F.lit(1)).alias("n"))

        def put(batch: DataFrame, batch_id: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

        query = state.writeStream.outputMode("update").foreachBatch(put).option("checkpointLocation", f"{root}/checkpoint").trigger(availableNow=True).start()
        query.awaitTermination()
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    schema = T.StructType([*[f for f in log.schema if f.name == "digest"], T.StructField("keep", log.schema["at"].dataType), T.StructField("n", T.LongType())])
    if not _exists(spark, out):  # only empty logs so far
        return spark.createDataFrame([], schema)
    return spark.read.schema(T.StructType([*schema, T.StructField("batch", T.LongType())])).parquet(out)


def _exists(spark, path: str) -> bool:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark._jsc.hadoopConfiguration()).exists(where)


def _content(here: DataFrame, id_col: str, text_col: str) -> DataFrame:
    doc = field(id_col).cast("long")
    # whether the id is null comes first, so that nulls sort last
    at = F.struct(doc.isNull().alias("no"), doc.alias("doc"), FILE, ROW)
    return here.select(at.alias("at"), squeezed(field(text_col)).alias("text"))


def _groups(here: DataFrame, archive: DataFrame | None, id_col: str, text_col: str, digest, files_per_batch: int | None, state_dir: str | None, run: str) -> DataFrame:
    spark = here.sparkSession
    mark = scratch_mark()
    content = _content(here, id_col, text_col)
    earlier = content if archive is None else _content(archive, id_col, text_col)
    root = state_dir.rstrip("/") if state_dir else scratch_path(spark, "xd")
    log_path = f"{root}/log/{run}"
    if not _exists(spark, f"{log_path}/_SUCCESS"):  # a run that is repeated finds its arrivals in the log
        content.select(digest(F.col("text")).alias("digest"), "at", sha256_digest(F.col("text")).alias("sha")).write.mode("overwrite").parquet(log_path)
    log = spark.read.parquet(log_path)
    told = retain(log, root, files_per_batch)
    if state_dir or files_per_batch:
        told = told.groupBy("digest").agg(F.max_by("keep", "batch").alias("keep"), F.max_by("n", "batch").alias("n"))
        if state_dir:
            told = told.join(log.select("digest").distinct(), "digest", "left_semi")
    state = materialise(told.select("digest", "keep", "n"), "xd-owners")

    groups = materialise(state.where("n > 1").select("digest", "keep", F.ceil(F.col("n") / HITS_PER_SALT).cast("int").alias("fan")), "xd-groups")
    small = bounded_broadcast(groups, BROADCAST_ROWS)
    hits = content.select(digest(F.col("text")).alias("digest"), "at", "text").join(small, "digest").where("at <> keep")
    hits = hits.select("digest", "at", "text", F.pmod(F.xxhash64("at"), F.col("fan")).cast("int").alias("salt"))
    owners = earlier.join(small.select(F.col("keep").alias("at"), "digest", "fan"), "at")
    owners = owners.select("digest", F.col("text").alias("kept_text"), F.explode(F.sequence(F.lit(0), F.col("fan") - 1)).alias("salt"))
    differ = materialise(hits.join(owners, ["digest", "salt"]).where("text <> kept_text").select("digest").distinct(), "xd-differ")

    named = join_groups(log, state, "digest", "n", BROADCAST_ROWS).select("at", "sha", "digest", "keep", "n")
    keep = [state, root]
    if not differ.isEmpty():
        # a digest that different texts share: all its texts that have arrived form groups of their own
        mixed = bounded_broadcast(differ, BROADCAST_ROWS)
        regroup = earlier.select(digest(F.col("text")).alias("digest"), "at", sha256_digest(F.col("text")).alias("sha"), "text").join(mixed, "digest")
        regroup = materialise(regroup.groupBy("digest", "sha", "text").agg(F.min("at").alias("keep2"), F.count(F.lit(1)).alias("n2")).drop("text"), "xd-regroup")
        named = named.join(bounded_broadcast(regroup, BROADCAST_ROWS), ["digest", "sha"], "left").select("at", "sha", F.coalesce("keep2", "keep").alias("keep"), F.coalesce("n2", "n").alias("n"))
        keep.append(regroup)
    drop_scratch(spark, mark, tuple(keep))
    return named


def _result(named: DataFrame, id_col: str) -> DataFrame:
    return named.select(
        F.col("at.doc").alias(id_col),
        F.col("keep.doc").alias("keep_id"),
        F.col("n").cast("long").alias("group_size"),
        (F.col("at") == F.col("keep")).alias("kept"),
        F.col("sha").alias("text_sha256"),
        F.col(f"at.{FILE}").alias(FILE),
        F.col(f"at.{ROW}").alias(ROW),
    )


def exact_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest=sha256_digest, files_per_batch: int | None = None,
    state_dir: str | None = None, run: str = "0", archive: DataFrame | None = None,
) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256, and its locator (file, row).

    Texts are equal when their bytes are, after each run of white space became one space; null
    text counts as empty. The smallest id of a group stays; a null id sorts last, and among
    repeated rows with that id exactly one is kept. ``digest`` may be any function of the text: a
    weak one costs time, never a wrong group. Other columns are ignored, so their names cannot clash. An empty table gives no row.

    ``state_dir`` (in storage that all executors share) keeps the state for later runs, each under a ``run`` name of its own;
    a run that is repeated under its name after a failure counts its rows once. ``archive`` is then a file scan
    with everything that has arrived, this run included, where retained texts are found by their locators. Sizes
    and kept rows are those so far: a later arrival with a smaller id takes over.
    """
    return _result(_groups(located(docs), None if archive is None else located(archive), id_col, text_col, digest, files_per_batch, state_dir, run), id_col)


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows that stay, with all their columns."""
    here = located(docs)
    mark = scratch_mark()
    gone = materialise(_result(_groups(here, None, id_col, text_col, sha256_digest, None, None, "0"), id_col).where(~F.col("kept")).select(FILE, ROW), "xd-gone")
    drop_scratch(docs.sparkSession, mark, (gone,))
    return unpacked(here.join(bounded_broadcast(gone, BROADCAST_ROWS), [FILE, ROW], "left_anti"), docs.columns)
