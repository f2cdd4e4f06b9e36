"""Shared helpers: scratch tables, bounded broadcasts, salted joins, hot-key-safe plumbing."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.utils import AnalysisException

#: White space that separates words (fixed value): space and tab to carriage return.
WS = r"[\x20\x09-\x0D]+"
NOT_WS = r"[^\x20\x09-\x0D]+"

_own_dir: list[str] = []
#: Scratch tables that this driver made and has not dropped yet, oldest first.
_made: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as ``spark.checkpoint.dir`` names it.

    Only a local master (tests) may go without: a folder of its own is made then. On a cluster a missing setting is an error.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    if not _own_dir:
        _own_dir.append("file://" + tempfile.mkdtemp(prefix="overlapgraph-"))
    return _own_dir[0]


def scratch_path(spark: SparkSession, name: str) -> str:
    _made.append(f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    return _made[-1]


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage through a table in the shared folder; survives the loss of executors."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch = path
    return out


def scratch_mark() -> int:
    """The present number of scratch tables, for ``drop_scratch``."""
    return len(_made)


def drop_scratch(spark: SparkSession, since: int = 0, keep: tuple = ()) -> None:
    """Delete the scratch tables made after a mark, except those of the frames or paths in ``keep``.

    Operators return lazy frames over scratch tables, so they drop only what their result does not read; call this
    without a mark once all results are stored.
    """
    kept = {getattr(k, "scratch", k) for k in keep}
    jvm = spark._jvm
    for path in [p for p in _made[since:] if p not in kept]:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
        _made.remove(path)


#: Bytes that one broadcast may hold; a table's rows are counted and its variable columns measured.
BROADCAST_BYTES = 48 << 20


def _width(kind: T.DataType) -> int:
    return sum(_width(f.dataType) for f in kind.fields) if isinstance(kind, T.StructType) else 8


def small_enough(df: DataFrame, max_rows: int, max_bytes: int = BROADCAST_BYTES) -> bool:
    """Whether a table has at most ``max_rows`` rows and about ``max_bytes`` bytes; reads no more than that many rows."""
    width, flexible = 16, F.lit(0).cast("long")
    for f in df.schema:
        if f.dataType.typeName() in ("string", "binary"):
            flexible = flexible + F.coalesce(F.octet_length(f.name), F.lit(0))
        elif f.dataType.typeName() == "array":
            flexible = flexible + F.greatest(F.size(f.name), F.lit(0)) * 16
        width += _width(f.dataType)
    n, size = df.limit(max_rows + 1).agg(F.count(F.lit(1)), F.coalesce(F.sum(flexible), F.lit(0))).first()
    return n <= max_rows and n * width + size <= max_bytes


def bounded_broadcast(df: DataFrame, max_rows: int, max_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Mark for broadcast only below a checked number of rows and bytes; a shuffle join serves beyond it."""
    return F.broadcast(df) if small_enough(df, max_rows, max_bytes) else df


#: A group with more rows than this is joined by broadcast of its key; a smaller one may meet in one task.
HOT_ROWS = 100_000


def join_groups(rows: DataFrame, groups: DataFrame, key: str, size: str, max_rows: int) -> DataFrame:
    """Rows joined to their groups (one row per key, with its number of rows) so that no task gets a hot group.

    Hot groups are at most one for ``HOT_ROWS`` rows; they are broadcast below the checked bound, and beyond it
    adaptive execution splits them.
    """
    if small_enough(groups, max_rows):
        return rows.join(F.broadcast(groups), key)
    hot = groups.where(F.col(size) > HOT_ROWS)
    if hot.isEmpty() or not small_enough(hot, max_rows):
        return rows.join(groups, key)
    rest = rows.join(F.broadcast(hot.select(key)), key, "left_anti").join(groups.where(F.col(size) <= HOT_ROWS), key)
    return rows.join(F.broadcast(hot), key).unionByName(rest)


#: Rows and bytes of the Arrow batches that carry whole texts between the JVM and Python.
ARROW_ROWS, ARROW_BYTES = 500, 8 << 20


def text_batches(df: DataFrame) -> DataFrame:
    """The same frame, its session set to small Arrow batches: ten thousand long texts in one batch would not fit a worker.

    These are settings of queries, not of the start of a session; smaller values that are already set stay.
    """
    conf = df.sparkSession.conf
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", ARROW_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", ARROW_BYTES)):
        now = conf.get(key, None)
        if now is None or not now.isdigit() or not 0 < int(now) <= most:
            conf.set(key, str(most))
    return df


#: A located row: all its columns as one struct, and the locator (hash of the file, row in it).
REC, FILE, ROW = "rec", "file", "row"
#: Plans whose rows are rows of a file, each at most once.
_SCANS = {"Project", "Filter", "SubqueryAlias", "LogicalRelation"}


def _is_scan(docs: DataFrame) -> bool:
    node = docs._jdf.queryExecution().analyzed()
    while True:
        if node.nodeName() not in _SCANS:
            return False
        below = node.children()
        if below.size() == 0:
            return True
        node = below.head()


def located(docs: DataFrame) -> DataFrame:
    """Rows (rec, file, row): the input row as a struct and its locator, stable over re-reads.

    The columns are inside the struct, so no name of theirs can clash. A frame that is no plain file scan is
    staged in the shared folder first, so that later reads see the same rows.
    """
    rec = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias(REC)
    if "_metadata" not in docs.columns and _is_scan(docs):
        try:
            return docs.select(rec, F.xxhash64("_metadata.file_path").alias(FILE), F.col("_metadata.row_index").alias(ROW))
        except AnalysisException:
            pass  # a scan without row numbers
    return materialise(docs.select(rec, F.lit(0).cast("long").alias(FILE), F.monotonically_increasing_id().alias(ROW)), "content")


def field(name: str) -> Column:
    """A column of a located row."""
    return F.col(REC).getField(name)


def unpacked(here: DataFrame, columns: list[str]) -> DataFrame:
    """The rows of a located frame as they were."""
    return here.select(*[field(c).alias(c) for c in columns])


def text_of(col: str | Column) -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def squeezed(col: str | Column) -> Column:
    """Text with each run of white space replaced by one space; null counts as empty."""
    return F.regexp_replace(text_of(col), WS, " ")


def held_out(id_col: str) -> Column:
    """True for the test fold: crc32 of the id as text leaves 1 when divided by 3."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
