"""Quotation linking: from messages with nested quotes to reply-ordered conversations without them.

Lines that begin with one or more ``>`` are quoted; the number of marks is their level. Runs of
lines of one level are passages. A passage is cut into units (the whole, paragraphs, lines, sentences), which are
normalised, hashed and joined to the earliest message of its conversation that has the same unit in its own
words, the texts being compared on a hit. The longest unit found links the passage, so excerpts are linked
too; less than a line or a sentence is not. A message replies to the original of its longest level-1 link. Only functions of Spark
SQL are used; the originals are reduced to one row per hash before the join, so no common passage makes pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, text_of

_MARK = r"^[ \t]*((?:>[ \t]?)+)"
_QUOTED = r"(?m)^[ \t]*>"
#: The line that introduces a quotation (fixed value).
_INTRO = r"(?i)\bwrote:[ \t]*$"


def normal(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def _units(said: Column) -> Column:
    """The whole of a message's own text or of a passage, its paragraphs, lines and sentences, normalised, each once."""
    parts = F.concat(F.array(said), F.split(said, r"\n[ \t]*\n"), F.split(said, r"\n"), F.split(said, r"(?<=[.!?])\s+|\n[ \t]*\n"))
    return F.filter(F.array_distinct(F.transform(parts, normal)), lambda u: u != "")


def link_quotes(messages: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One row per input row: conv, turn, role, own_text, n_quotes, n_linked, max_level, parent_turn, root_turn, reply_path.

    ``own_text`` is the text without quoted lines and their introductions, trimmed (the text as
    it is where nothing is quoted; null counts as empty). ``parent_turn`` is null where no level-1 quotation has an earlier
    original; ``reply_path`` lists the zero-padded turns from the root to the message, so that sorting by it
    puts every reply after its parent. Rows with a null conversation or turn are never linked, and have no
    path. Repeated rows give equal rows; of two texts with one turn, the first parent counts for the path; of units of one
    length the one from the latest turn links. A path is as long as its chain of replies, as its rows name every ancestor. An empty table gives no row.
    """
    base = messages.select(F.col(conv_col).alias("conv"), F.col(turn_col).cast("long").alias("turn"), F.col(role_col).alias("role"), text_of(text_col).alias("text"))
    has = F.col("text").rlike(_QUOTED)
    key = ["conv", "turn", "sha"]
    quoting = base.where(has).select("conv", "turn", F.sha2(F.col("text").cast("binary"), 256).alias("sha"), "text").distinct()
    lines = quoting.select(*key, F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    mark = F.regexp_extract("line", _MARK, 1)
    lines = lines.withColumn("level", F.length(F.regexp_replace(mark, "[^>]", ""))).withColumn("said", F.trim(F.regexp_replace("line", _MARK, "")))
    inside = Window.partitionBy(*key).orderBy("pos")
    lines = lines.withColumn("next", F.lead("level", 1, 0).over(inside)).withColumn("before", F.lag("level", 1, -1).over(inside))
    lines = lines.withColumn("run", F.sum(F.when(F.col("level") != F.col("before"), 1).otherwise(0)).over(inside))
    intro = (F.col("level") == 0) & (F.col("next") > 0) & F.col("line").rlike(_INTRO)
    joined = lambda col, sep: F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", col))), lambda x: x[col]), sep)
    # a message's lines meet again: a group is never larger than one input row
    runs = lines.where(~intro).groupBy(*key, "run", "level").agg(joined("said", "\n").alias("said"), joined("line", "\n").alias("lines"))
    runs = materialise(runs, "ql-runs")
    own = runs.groupBy(*key).agg(
        F.array_join(F.transform(F.array_sort(F.collect_list(F.when(F.col("level") == 0, F.struct("run", "lines")))), lambda x: x["lines"]), "\n").alias("own"),
        F.count(F.when(F.col("level") > 0, 1)).alias("n_quotes"),
        F.max("level").alias("max_level"),
    ).withColumn("own", F.regexp_replace("own", r"^\s+|\s+$", ""))
    passages = runs.where("level > 0 and conv is not null and turn is not null").select(*key, "run", "level", F.explode(_units(F.col("said"))).alias("unit"))
    convs = passages.select("conv").distinct()
    plain = base.where(~has).join(convs, "conv", "left_semi").select("conv", "turn", F.col("text").alias("own"))
    said = plain.unionByName(own.select("conv", "turn", "own")).where("conv is not null and turn is not null")
    originals = said.select("conv", "turn", F.explode(_units(F.col("own"))).alias("unit"))
    originals = originals.groupBy("conv", F.xxhash64("unit").alias("h"), "unit").agg(F.min("turn").alias("from_turn"))
    found = passages.withColumn("h", F.xxhash64("unit")).join(originals, ["conv", "h", "unit"]).where("from_turn < turn")
    best = found.groupBy(*key, "run", "level").agg(F.max(F.struct(F.length("unit").alias("n"), "from_turn")).alias("best"))
    links = best.groupBy(*key).agg(F.count(F.lit(1)).alias("n_linked"), F.max(F.when(F.col("level") == 1, F.col("best")))["from_turn"].alias("parent_turn"))
    info = materialise(own.join(links, key, "left"), "ql-info")

    step = info.where("parent_turn is not null").groupBy("conv", "turn").agg(F.min("parent_turn").alias("up"))
    step = step.select("conv", "turn", "up", _pad("turn").alias("tail"))
    step = materialise(step, "ql-step")
    # pointer doubling: each round doubles the part of the chain that a row has seen
    while not step.isEmpty():
        above = step.select("conv", F.col("turn").alias("up"), F.col("up").alias("up2"), F.col("tail").alias("tail2"))
        both = step.join(above, ["conv", "up"], "left")
        grown = both.select("conv", "turn", F.coalesce("up2", "up").alias("up"), F.when(F.col("up2").isNull(), F.col("tail")).otherwise(F.concat("tail2", F.lit("/"), "tail")).alias("tail"), F.col("up2").isNotNull().alias("more"))
        grown = materialise(grown, "ql-step")
        step = grown.drop("more")
        if grown.where("more").isEmpty():
            break
    paths = step.select("conv", "turn", F.col("up").alias("root_turn"), F.concat(_pad("up"), F.lit("/"), "tail").alias("path"))

    rest = base.where(~has).select("conv", "turn", "role", F.col("text").alias("own_text"), F.lit(0).cast("long").alias("n_quotes"), F.lit(0).cast("long").alias("n_linked"), F.lit(0).cast("long").alias("max_level"), F.lit(None).cast("long").alias("parent_turn"))
    a = base.where(has).select("conv", "turn", "role", F.sha2(F.col("text").cast("binary"), 256).alias("sha")).alias("a")
    b = info.alias("b")
    same = F.col("a.conv").eqNullSafe(F.col("b.conv")) & F.col("a.turn").eqNullSafe(F.col("b.turn")) & (F.col("a.sha") == F.col("b.sha"))
    told = a.join(b, same, "left").select("a.conv", "a.turn", "a.role", F.coalesce("b.own", F.lit("")).alias("own_text"), F.coalesce("b.n_quotes", F.lit(0).cast("long")).alias("n_quotes"), F.coalesce("b.n_linked", F.lit(0).cast("long")).alias("n_linked"), F.coalesce("b.max_level", F.lit(0)).cast("long").alias("max_level"), "b.parent_turn")
    told = told.join(paths, ["conv", "turn"], "left")
    rest = rest.withColumn("root_turn", F.lit(None).cast("long")).withColumn("path", F.lit(None).cast("string"))
    every = rest.unionByName(told)
    known = F.col("conv").isNotNull() & F.col("turn").isNotNull()
    return every.select(
        F.col("conv").alias(conv_col), F.col("turn").alias(turn_col), F.col("role").alias(role_col), "own_text", "n_quotes", "n_linked", "max_level", "parent_turn",
        F.when(known, F.coalesce("root_turn", "turn")).alias("root_turn"), F.when(known, F.coalesce("path", _pad("turn"))).alias("reply_path"),
    )


def _pad(col: str) -> Column:
    """A turn as text that sorts as the number does, for every 64-bit number."""
    c = F.col(col)
    below = (c.cast("decimal(20,0)") + F.lit(9223372036854775807) + 1).cast("string")
    return F.when(c >= 0, F.lpad(c.cast("string"), 19, "0")).otherwise(F.concat(F.lit("-"), F.lpad(below, 19, "0")))
