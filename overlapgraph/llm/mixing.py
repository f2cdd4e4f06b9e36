"""Mixing sources to target weights by systematic sampling.

Each document of a source has the same expected number of copies, target / size of the source.
Prefix sums of these expectations, in an order by size within the source, plus one random
offset per source: a document is emitted once for every integer its interval crosses.
The order by size makes the taken words follow the target closely. Inside a size class the order is that of
a hash of id and text, so it is the same in every run whatever the ids are; rows equal in both are interchangeable.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import FILE, NOT_WS, ROW, bounded_broadcast, drop_scratch, field, located, materialise, scratch_mark, text_of, unpacked

WEIGHTS = (5, 2, 1)
MAX_REPEATS = 3
SEED = "mix-1"
#: Up to this many (source, size class) rows are broadcast; beyond it the joins shuffle.
BROADCAST_ROWS = 200_000
#: A block that holds more rows than this beyond four times its share (of equal ids and texts) is cut by the rows' places.
BLOCK_ROWS = 10_000


def words_in(text: Column) -> Column:
    return F.regexp_count(text_of(text), F.lit(NOT_WS)).cast("long")


def order_tag(doc: Column, text: Column) -> Column:
    """The first 32 bits of a hash of id and text; a null id counts as an empty one, null text as empty."""
    named = F.concat(F.coalesce(doc.cast("string"), F.lit("")), F.lit(":"), text_of(text))
    return F.conv(F.substring(F.md5(named.cast("binary")), 1, 8), 16, 10).cast("long")


def _slim(here: DataFrame, id_col: str, text_col: str, source_col: str) -> DataFrame:
    doc, text = field(id_col).cast("long"), field(text_col)
    return here.select(doc.alias("doc"), source_key(field(source_col)).alias("src"), words_in(text).alias("words"), order_tag(doc, text).alias("tag"), FILE, ROW)


def targets(cells: DataFrame, weights: tuple = WEIGHTS, max_repeats: int = MAX_REPEATS) -> DataFrame:
    """(source key, words) to (src, source_size, target): shares by weight, capped, the excess reshared.

    Sources in order of their ratio of cap to weight: the capped ones come first, so the share of
    the rest per unit of weight is known from prefix sums. The table has one row per source.
    """
    per = cells.groupBy("src").agg(F.sum("words").alias("source_size"))
    place = F.row_number().over(Window.orderBy("src")) - 1
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (place % len(weights) + 1).cast("int"))
    per = per.withColumn("w", w).withColumn("cap", (F.col("source_size") * max_repeats).cast("double"))
    every, before = Window.partitionBy(), Window.orderBy(F.col("cap") / F.col("w"), "src").rowsBetween(Window.unboundedPreceding, -1)
    total = F.sum("source_size").over(every).cast("double")
    left_w = F.sum("w").over(every) - F.coalesce(F.sum("w").over(before), F.lit(0.0))
    share = (total - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / left_w
    per = per.withColumn("share", share).withColumn("capped", F.col("cap") / F.col("w") <= F.col("share"))
    level = F.max(F.when(~F.col("capped"), F.col("share"))).over(every)
    return per.select("src", "source_size", F.when(F.col("capped"), F.col("cap")).otherwise(level * F.col("w")).alias("target"))


def mix_slim(slim: DataFrame, seed: str = SEED, weights: tuple = WEIGHTS, max_repeats: int = MAX_REPEATS) -> DataFrame:
    """Rows (src, doc, words, tag, file, row) with source_size, target, copies."""
    # a size class keeps the four leading bits of the size
    shift = "cast(greatest(length(bin(words)) - 4, 0) as int)"
    slim = slim.withColumn("cls", F.expr(f"shiftleft(shiftright(words, {shift}), {shift})"))
    cells = slim.groupBy("src", "cls").agg(F.count(F.lit(1)).alias("cnt"), F.sum("words").alias("words"))
    cells = materialise(cells, "mix-cells")
    goal = targets(cells, weights, max_repeats)
    upto = Window.partitionBy("src").orderBy("cls").rowsBetween(Window.unboundedPreceding, -1)
    cell = cells.withColumn("cell_at", F.coalesce(F.sum("cnt").over(upto), F.lit(0))).withColumn("fan", F.ceil(F.sqrt("cnt")).cast("long"))
    offset = F.conv(F.substring(F.md5(F.concat(F.lit(seed + ":"), F.col("src")).cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
    cell = cell.join(goal, "src").withColumn("offset", offset)
    cell = materialise(cell.drop("words"), "mix-goal")
    cell_b = bounded_broadcast(cell, BROADCAST_ROWS)
    # a cell of c rows is cut into sqrt(c) blocks of about sqrt(c) rows, so no window holds a hot source
    placed = slim.join(cell_b, ["src", "cls"]).withColumn("sub", F.pmod("tag", "fan"))
    counts = materialise(placed.groupBy("src", "cls", "sub", "fan").agg(F.count(F.lit(1)).alias("c")), "mix-counts")
    hot = counts.where(F.col("c") > 4 * F.col("fan") + BLOCK_ROWS).select("src", "cls", "sub", F.ceil(F.col("c") / BLOCK_ROWS).alias("cuts"))
    placed = placed.join(bounded_broadcast(hot, BROADCAST_ROWS), ["src", "cls", "sub"], "left").withColumn("cut", F.pmod(F.xxhash64(FILE, ROW), F.coalesce("cuts", F.lit(1)))).drop("cuts")
    inside = Window.partitionBy("src", "cls").orderBy("sub", "cut").rowsBetween(Window.unboundedPreceding, -1)
    if not hot.isEmpty():
        counts = placed.groupBy("src", "cls", "sub", "cut").agg(F.count(F.lit(1)).alias("c"))
    else:
        counts = counts.withColumn("cut", F.lit(0).cast("long"))
    blocks = counts.withColumn("block_at", F.coalesce(F.sum("c").over(inside), F.lit(0))).select("src", "cls", "sub", "cut", "block_at")
    blocks = bounded_broadcast(materialise(blocks, "mix-blocks"), BROADCAST_ROWS)
    rank = F.row_number().over(Window.partitionBy("src", "cls", "sub", "cut").orderBy("words", F.col("doc").asc_nulls_last(), "tag", FILE, ROW))
    ranked = placed.join(blocks, ["src", "cls", "sub", "cut"]).withColumn("rank", F.col("cell_at") + F.col("block_at") + rank)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    copies = F.floor(F.col("offset") + rate * F.col("rank")) - F.floor(F.col("offset") + rate * (F.col("rank") - 1))
    return ranked.select("src", "doc", "words", FILE, ROW, "source_size", "target", copies.cast("long").alias("copies"))


def source_key(source: Column) -> Column:
    """Sources by code point with null last: the key sorts that way and tells null from empty."""
    return F.when(source.isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), source.cast("string")))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: str = SEED) -> DataFrame:
    """One row per input row: id, size, source_size, target, copies, taken.

    Null text has size 0; a null source is a source of its own and comes last. Documents of size
    0 take part like others and take no words. Null and repeated ids are told apart by their texts; repeated rows
    are separate documents. Only these three columns are read, so no other name can clash. An empty table gives no row.
    """
    slim = _slim(located(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(source_col).alias("source"))), "id", "text", "source")
    out = mix_slim(materialise(slim, "mix-slim"), seed)
    return out.select(
        F.col("doc").alias(id_col), F.col("words").alias("size"), "source_size", "target", "copies", (F.col("words") * F.col("copies")).cast("long").alias("taken")
    )


#: Up to this many decisions (24 bytes each) are broadcast to the documents; beyond it the join shuffles.
BROADCAST_DECISIONS = 500_000


def emit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: str = SEED) -> DataFrame:
    """The mix itself: every row as often as it is taken, with all its columns."""
    here = located(docs)
    mark = scratch_mark()
    taken = mix_slim(materialise(_slim(here, id_col, text_col, source_col), "mix-slim"), seed).where("copies > 0")
    taken = materialise(taken.select(FILE, ROW, F.sequence(F.lit(1).cast("long"), F.col("copies")).alias("each")), "mix-taken")
    drop_scratch(docs.sparkSession, mark, (taken,))
    out = here.join(bounded_broadcast(taken, BROADCAST_DECISIONS), [FILE, ROW])
    return unpacked(out.select("rec", F.explode("each")), docs.columns)
