"""Near-duplicate classes by probability-weighted minwise hashing, banding and verification.

A document is a weighted set of five-word shingles (lower case, blanks as separators; a text
of one to four words is one shingle). Each shingle is a Poisson process whose rate is its
weight, ``1 + ln(count)``; every arrival picks one register, and a register keeps the shingle of
its earliest arrival. A shingle stops as soon as its next arrival would be later than the latest
register, so work is about n + k ln k for n shingles and k registers. Two documents
agree in a register with their probability Jaccard similarity J, and two documents are similar when the exact
J of their weighted shingles reaches the threshold; where no shingle repeats, J is the Jaccard similarity of the sets.
With 48 bands of 8 registers a pair with J = 0.8 shares a bucket with probability 0.9998.

With o and o' the shares of the two weights that lie on common shingles, 1/J >= 1/o + 1/o' - 1: a common shingle
whose weights have the shares p and p' adds at most 1 / (1/p + (1 - o')/p') to J, a function that is concave and
grows in proportion, so its sum is at most its value at the sums o and o'. Hence J >= s needs o, o' >= s, and one
of them at least 2s/(1+s). The size test and the exact join below rest on this bound.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textvec as tv
from .common import FILE, ROW, bounded_broadcast, drop_scratch, field, join_groups, located, materialise, scratch_mark, squeezed, text_batches, text_of, unpacked
from .components import components

SHINGLE_WORDS = 5
SIMILARITY = 0.8
BANDS, ROWS = 48, 8
#: Room for rounding where a similarity or a share is held against a bound.
EPS = 1e-9


def shingle_sets(texts: list[str], words: int = SHINGLE_WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document index, shingle hash, count), sorted by both; texts without words have no row."""
    block = tv.Block([t.lower() for t in texts])
    h = block.word_hashes()
    per_doc = np.bincount(block.w_doc, minlength=block.n)
    first = np.concatenate([[0], np.cumsum(per_doc)[:-1]])
    rank = np.arange(len(h)) - first[block.w_doc]
    whole = per_doc[block.w_doc]
    start = np.flatnonzero((rank <= whole - words) | (rank == 0))
    acc = np.zeros(len(start), np.uint64)
    limit = (first + per_doc)[block.w_doc[start]]
    for j in range(words):
        at = start + j
        inside = at < limit
        part = np.where(inside, h[np.minimum(at, len(h) - 1)] if len(h) else 0, np.uint64(0))
        acc = tv.mix(acc * np.uint64(0x100000001B3) + part)
    doc = block.w_doc[start]
    order = np.lexsort((acc, doc))
    doc, acc = doc[order], acc[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (acc[1:] != acc[:-1])
    at = np.flatnonzero(new)
    count = np.diff(np.append(at, len(doc)))
    return doc[at], acc[at], count


def signatures(doc: np.ndarray, shingle: np.ndarray, weight: np.ndarray, n_docs: int, k: int) -> np.ndarray:
    """The winning shingle of each of ``k`` registers of each document; rows of zeros for empty ones."""
    best = np.full(n_docs * k, np.inf)
    won = np.zeros(n_docs * k, np.uint64)
    latest = np.full(n_docs, np.inf)
    x = np.zeros(len(doc))
    alive = np.arange(len(doc))
    turn = 0
    while len(alive):
        turn += 1
        d, s = doc[alive], shingle[alive]
        r = tv.mix(s ^ tv.mix(np.full(1, turn, np.uint64))[0])
        gap = -np.log1p(-((r >> np.uint64(11)).astype(np.float64) * 2.0**-53)) / weight[alive]
        x = x + gap
        keep = x < latest[d]
        if not keep.all():
            alive, d, s, r, x = alive[keep], d[keep], s[keep], r[keep], x[keep]
        cell = d * k + (tv.mix(r) % np.uint64(k)).astype(np.int64)
        better = np.flatnonzero(x < best[cell])
        if len(better):
            order = better[np.argsort(-x[better], kind="stable")]  # the earliest arrival is written last
            best[cell[order]] = x[order]
            won[cell[order]] = s[order]
            touched = np.unique(d[better])
            latest[touched] = best.reshape(n_docs, k)[touched].max(axis=1)
    return won.reshape(n_docs, k)


def band_keys(sig: np.ndarray, bands: int, rows: int) -> np.ndarray:
    acc = np.tile(np.arange(1, bands + 1, dtype=np.uint64), (len(sig), 1))
    cut = sig.reshape(len(sig), bands, rows)
    for j in range(rows):
        acc = tv.mix(acc * np.uint64(0x100000001B3) + cut[:, :, j])
    return acc.view(np.int64)


def weights(count: np.ndarray) -> np.ndarray:
    return 1.0 + np.log(count)


def sketch(texts: list[str], bands: int = BANDS, rows: int = ROWS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(band keys, number of distinct shingles, sum of their weights) of a block of texts."""
    doc, shingle, count = shingle_sets(texts)
    w = weights(count)
    sig = signatures(doc, shingle, w, len(texts), bands * rows)
    return band_keys(sig, bands, rows), np.bincount(doc, minlength=len(texts)), np.bincount(doc, weights=w, minlength=len(texts)).astype(np.float64)


def similarity_of(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """The exact probability Jaccard similarity of two weighted sets (sorted members, weights).

    For a common member d, max(a_e/a_d, b_e/b_d) is a_e/a_d where the ratio a_e/b_e is at least that of d, and
    b_e/b_d elsewhere; so sums along the common members sorted by their ratio give all the terms.
    """
    (s, v), (t, w) = a, b
    _, i, j = np.intersect1d(s, t, assume_unique=True, return_indices=True)
    if not len(i):
        return 0.0
    x, y = v[i], w[j]
    ratio = x / y
    order = np.argsort(ratio, kind="stable")
    x, y, ratio = x[order], y[order], ratio[order]
    first = np.searchsorted(ratio, ratio, side="left")
    above = np.append(np.cumsum(x[::-1])[::-1], 0.0)[first] + (v.sum() - x.sum())
    below = np.append(0.0, np.cumsum(y))[first] + (w.sum() - y.sum())
    return float(np.sum(1.0 / (above / x + below / y)))


def probability_jaccard(a: dict, b: dict) -> float:
    """The same by its definition, for tests."""
    total = 0.0
    for d in a.keys() & b.keys():
        total += 1.0 / sum(max(a.get(e, 0) / a[d], b.get(e, 0) / b[d]) for e in a.keys() | b.keys())
    return total


def _sketch_batches(batches: Iterator[pa.RecordBatch], bands: int, rows: int) -> Iterator[pa.RecordBatch]:
    for batch in tv.pieces(batches):
        ids, texts = batch.column(0), batch.column(1).to_pylist()
        for a, b in tv.blocks(texts):
            keys, n, w = sketch(texts[a:b], bands, rows)
            flat = pa.array(keys.reshape(-1))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, keys.size + 1, bands, dtype=np.int32)), flat)
            yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(n.astype(np.int64)), pa.array(w), lists], ["id", "n", "w", "keys"])


def _verify_batches(batches: Iterator[pa.RecordBatch], similarity: float) -> Iterator[pa.RecordBatch]:
    for batch in tv.pieces(batches):
        a_id, b_id = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        left, right = batch.column(2), batch.column(3)
        out = []
        known: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        size = 0
        for i in range(batch.num_rows):
            pair = []
            for key, col in ((a_id[i], left), (b_id[i], right)):
                got = known.get(key)
                if got is None:
                    if size > 1 << 18:
                        known, size = {}, 0
                    _, members, count = shingle_sets([col[i].as_py()])
                    got = known[key] = members, weights(count)
                    size += len(members)
                pair.append(got)
            out.append(similarity_of(*pair))
        sim = np.array(out, np.float64)
        ok = sim >= similarity - EPS
        yield pa.RecordBatch.from_arrays([pa.array(a_id[ok]), pa.array(b_id[ok]), pa.array(sim[ok])], ["a", "b", "sim"])


def _shingle_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in tv.pieces(batches):
        k, comp, texts = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2).to_pylist()
        for a, b in tv.blocks(texts):
            doc, shingle, count = shingle_sets(texts[a:b])
            w = weights(count)
            total, n = np.bincount(doc, weights=w, minlength=b - a)[doc], np.bincount(doc, minlength=b - a)[doc]
            cols = [pa.array(k[a:b][doc]), pa.array(comp[a:b][doc]), pa.array(n.astype(np.int64)), pa.array(total), pa.array(w), pa.array(shingle.view(np.int64))]
            yield pa.RecordBatch.from_arrays(cols, ["k", "comp", "n", "w", "a", "s"])


#: Up to this many ids or keys (at most 40 bytes each) are broadcast; beyond it the joins shuffle.
BROADCAST_ROWS = 300_000
#: Pairs that share a centre are split into groups of about this many before its text is joined.
PAIRS_PER_SALT = 64


def _digest(text_col: str) -> F.Column:
    return F.unhex(F.sha2(F.trim(squeezed(F.lower(text_of(text_col)))).cast("binary"), 256))


def _verified(pairs: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) whose exact shingle Jaccard similarity reaches the threshold.

    The second text is joined first (few pairs share it); the first, which may be the centre of
    a huge group, is repeated once for every ``PAIRS_PER_SALT`` of its pairs.
    """
    fan = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / PAIRS_PER_SALT).cast("int").alias("fan"))
    fan = bounded_broadcast(fan, BROADCAST_ROWS)
    salted = pairs.join(fan, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.col("fan")).cast("int").alias("salt"))
    with_b = salted.join(texts.select(F.col("k").alias("b"), F.col("text").alias("text_b")), "b")
    with_a = fan.join(texts.select(F.col("k").alias("a"), F.col("text").alias("text_a")), "a").select(
        "a", "text_a", F.explode(F.sequence(F.lit(0), F.col("fan") - 1)).alias("salt")
    )
    both = with_b.join(with_a, ["a", "salt"]).select("a", "b", "text_a", "text_b")
    schema = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType()), T.StructField("sim", T.DoubleType())])
    return both.mapInArrow(lambda it: _verify_batches(it, similarity), schema)


def _close_pairs(open_: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """Pairs (lo, hi) of texts of different components, among them all that reach the threshold.

    ``open_`` has rows (k, comp). A text's shingles are ordered by rarity, those of one component alone first. Of a similar pair one text
    has a share of at least 2s/(1+s) on common shingles and the other one of at least s. So the shingles of the first
    up to the point where less than 2s/(1+s) of its weight follows, and those of the second up to the
    point where less than s follows, have a member in common. Texts whose first shingles are their own meet nobody.
    """
    schema = "k long, comp long, n long, w double, a double, s long"
    few = texts.join(bounded_broadcast(open_, BROADCAST_ROWS), "k").select("k", "comp", "text")
    sets = materialise(few.mapInArrow(_shingle_batches, schema), "nd-shingles")
    shared = sets.groupBy("s").agg(F.count(F.lit(1)).alias("c"), F.min("comp").alias("x"), F.max("comp").alias("y")).where("x < y").select("s", "c")
    shared = bounded_broadcast(materialise(shared, "nd-common"), BROADCAST_ROWS)
    # a window holds the shingles of one text; ``rest`` and ``left`` are the share and number of this shingle and all that follow it
    on = Window.partitionBy("k").orderBy(F.desc("c"), F.desc("s")).rowsBetween(Window.unboundedPreceding, 0)
    first = sets.join(shared, "s").select("k", "comp", "n", "w", "s", (F.sum("a").over(on) / F.col("w")).alias("rest"), F.count(F.lit(1)).over(on).alias("left"))
    first = materialise(first.where(F.col("rest") >= similarity - EPS), "nd-prefix")
    most = 2 * similarity / (1 + similarity)
    x, y = first.where(F.col("rest") >= most - EPS).alias("x"), first.alias("y")
    # at the first common shingle no more than ``left`` members of either are common; all but n of a weight w are extra weight of some
    both = F.least("x.left", "y.left")
    o, o2 = (F.least(F.col(f"{t}.rest"), (F.col(f"{t}.w") - F.col(f"{t}.n") + both) / F.col(f"{t}.w")) for t in "xy")
    meet = (
        (F.col("x.s") == F.col("y.s"))
        & (F.col("x.comp") != F.col("y.comp"))
        & ((F.col("y.rest") < most - EPS) | (F.col("x.k") < F.col("y.k")))
        & (1 / o + 1 / o2 <= 1 + 1 / similarity + EPS)
    )
    return x.join(y, meet).select(F.least("x.k", "y.k").alias("lo"), F.greatest("x.k", "y.k").alias("hi")).distinct()


def _may_reach(n: str, w: str, n2: str, w2: str, similarity: float):
    """Whether the sizes of two texts allow the similarity: each weight is 1 at least, so at most (1 - s) W shingles are not common."""
    most = 1 - similarity
    return (F.col(n) - F.col(n2) <= most * F.col(w) + EPS) & (F.col(n2) - F.col(n) <= most * F.col(w2) + EPS)


def _classes(here: DataFrame, id_col: str, text_col: str, similarity: float, bands: int, rows: int) -> DataFrame:
    """Rows (doc, file, row, class_id, class_size, kept, n_links) of a located frame."""
    spark = here.sparkSession
    mark = scratch_mark()
    base = text_batches(here).select(field(id_col).cast("long").alias("doc"), FILE, ROW, text_of(field(text_col)).alias("text"))
    long, double = T.LongType(), T.DoubleType()
    at_type = T.StructType([T.StructField(FILE, long), T.StructField(ROW, long)])
    id_type = T.StructType([
        T.StructField("id", T.StructType([T.StructField("doc", long), T.StructField("at", at_type), T.StructField("digest", T.BinaryType())])),
        T.StructField("n", long), T.StructField("w", double), T.StructField("keys", T.ArrayType(long)),
    ])
    named = F.struct("doc", F.struct(FILE, ROW).alias("at"), _digest("text").alias("digest"))
    sketched = base.select(named.alias("id"), "text").mapInArrow(lambda it: _sketch_batches(it, bands, rows), id_type)
    rows_ = materialise(sketched.select("id.doc", "id.at", "id.digest", "n", "w", "keys"), "nd-sketch")
    order = F.struct(F.col("doc").isNull(), F.col("doc"), F.col("at"))
    copies = materialise(
        rows_.groupBy("digest")
        .agg(F.min(order).alias("first"), F.count(F.lit(1)).alias("copies"), F.first("n").alias("n"), F.first("w").alias("w"), F.first("keys").alias("keys"))
        .select("digest", "first", "copies", "n", "w", "keys", F.xxhash64("digest").alias("p"), F.monotonically_increasing_id().alias("k")),
        "nd-texts",
    )
    spread = copies.where("n > 0").select("k", "p", "n", "w", F.explode("keys").alias("key"))
    shared = spread.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 1")
    shared = materialise(shared, "nd-shared")
    members = materialise(spread.join(bounded_broadcast(shared, BROADCAST_ROWS), "key"), "nd-members")
    # a text that meets many others is the likely origin of its copies, and the best first centre
    met = materialise(members.groupBy("k").agg(F.sum("c").alias("met")), "nd-met")
    members = members.drop("c").join(bounded_broadcast(met, BROADCAST_ROWS), "k")
    # the text of each digest is read at the place of its first row, one row and no other
    wanted = materialise(copies.join(bounded_broadcast(met.select("k"), BROADCAST_ROWS), "k").select("k", F.col(f"first.at.{FILE}").alias(FILE), F.col(f"first.at.{ROW}").alias(ROW)), "nd-named")
    texts = materialise(base.join(bounded_broadcast(wanted, BROADCAST_ROWS), [FILE, ROW]).select("k", "text"), "nd-text")

    links, tried, label, turn = None, None, None, 0
    # what is left of the buckets: (key, k, p, n, w, met, comp); in the beginning each text is its own component
    state = members.withColumn("comp", F.col("k"))
    while True:
        turn += 1
        # the centre: in the first round the text that meets most others, later one of a small component
        pick = F.struct("k", "comp", "n", "w")
        if turn == 1:
            heads = state.groupBy("key").agg(F.max_by(pick, F.struct("met", "p")).alias("c"))
        else:
            weight = F.pmod(F.xxhash64("comp", "key", F.lit(turn)), F.lit(1 << 30)) * F.col("size")
            heads = state.groupBy("key", "comp").agg(F.count(F.lit(1)).alias("size"), F.min_by(pick, F.xxhash64("p", "key", F.lit(turn))).alias("head"))
            heads = heads.groupBy("key").agg(F.min_by("head", weight).alias("c"), F.count(F.lit(1)).alias("comps")).where("comps > 1").drop("comps")
        heads = materialise(heads, "nd-centres")
        placed = materialise(state.join(bounded_broadcast(heads, BROADCAST_ROWS), "key"), "nd-placed")
        lo, hi = F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")
        pairs = (
            placed.where((F.col("comp") != F.col("c.comp")) & _may_reach("n", "w", "c.n", "c.w", similarity))
            .select(F.col("c.k").alias("a"), F.col("k").alias("b"))
            .groupBy(lo, hi)
            .agg(F.min("a").alias("a"))
            .select("a", F.when(F.col("a") == F.col("lo"), F.col("hi")).otherwise(F.col("lo")).alias("b"), "lo", "hi")
        )
        if tried is not None:
            pairs = pairs.join(tried, ["lo", "hi"], "left_anti")
        pairs = materialise(pairs, "nd-pairs")
        found = materialise(_verified(pairs.select("a", "b"), texts, similarity), "nd-links")
        stalled = found.isEmpty()
        if not stalled:
            links = found if links is None else links.unionByName(found)
            label = components(links)
        tried = pairs.select("lo", "hi") if tried is None else tried.unionByName(pairs.select("lo", "hi"))
        # a centre has met every other component of its bucket and leaves it; a bucket of one component is done
        left = placed.where("k <> c.k").select("key", "k", "p", "n", "w", "met", "comp")
        if not stalled:
            left = left.drop("comp").join(bounded_broadcast(label, BROADCAST_ROWS).withColumnRenamed("v", "k"), "k", "left").select("key", "k", "p", "n", "w", "met", F.coalesce("root", "k").alias("comp"))
        left = materialise(left, "nd-left")
        open_ = left.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x < y").select("key")
        state = materialise(left.join(bounded_broadcast(materialise(open_, "nd-open"), BROADCAST_ROWS), "key"), "nd-state")
        # what a round leaves open goes on; the fixed centres of the first may all miss, so it alone hands nothing to the exact join
        if state.isEmpty() or (stalled and turn > 1):
            break

    still = materialise(state.select("k", "comp").distinct(), "nd-still")
    if not still.isEmpty():
        pairs = materialise(_close_pairs(still, texts, similarity).join(tried, ["lo", "hi"], "left_anti"), "nd-close")
        found = materialise(_verified(pairs.select(F.col("lo").alias("a"), F.col("hi").alias("b")), texts, similarity), "nd-links")
        if not found.isEmpty():
            links = found if links is None else links.unionByName(found)
            label = components(links)

    none = F.lit(0).cast("long")
    if links is None:
        classes = copies.select("digest", F.col("first.doc").alias("class_id"), F.col("first.at").alias("keep_at"), F.col("copies").alias("class_size"), none.alias("n_links"), "copies")
    else:
        degree = links.select(F.explode(F.array("a", "b")).alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n_links"))
        tagged = (
            copies.select("k", "digest", "first", "copies")
            .join(bounded_broadcast(label, BROADCAST_ROWS).withColumnRenamed("v", "k"), "k", "left")
            .join(bounded_broadcast(materialise(degree, "nd-degree"), BROADCAST_ROWS), "k", "left")
        )
        alone = tagged.where("root is null").select("digest", F.col("first.doc").alias("class_id"), F.col("first.at").alias("keep_at"), F.col("copies").alias("class_size"), none.alias("n_links"), "copies")
        together = materialise(tagged.where("root is not null"), "nd-linked")
        roots = materialise(together.groupBy("root").agg(F.min("first").alias("head"), F.sum("copies").alias("class_size"), F.count(F.lit(1)).alias("texts")), "nd-roots")
        linked = join_groups(together, roots, "root", "texts", BROADCAST_ROWS)
        linked = linked.select("digest", F.col("head.doc").alias("class_id"), F.col("head.at").alias("keep_at"), "class_size", F.coalesce("n_links", none).alias("n_links"), "copies")
        classes = alone.unionByName(linked)
    classes = materialise(classes, "nd-classes")
    out = join_groups(rows_.select("doc", "digest", "at"), classes, "digest", "copies", BROADCAST_ROWS)
    drop_scratch(spark, mark, (rows_, classes))
    return out.select("doc", F.col(f"at.{FILE}").alias(FILE), F.col(f"at.{ROW}").alias(ROW), "class_id", "class_size", (F.col("at") == F.col("keep_at")).alias("kept"), "n_links")


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = SIMILARITY, bands: int = BANDS, rows: int = ROWS
) -> DataFrame:
    """One row per input row: id, class_id, class_size, kept, n_links, and its locator (file, row).

    ``class_id`` is the smallest id in the class (connected component of verified links and exact
    copies); ``kept`` marks one row of each class; ``n_links`` counts the verified links of the
    row's text to other texts; only tested pairs count, and texts already in one class are not tested. Null text counts as empty, all texts without words are copies of each other; a null
    id sorts last, and a class with null ids alone has a null class_id. Repeated rows are
    copies. Other columns are ignored, so their names cannot clash. An empty table gives no row.

    Every bucket links its members to one centre, which then leaves the bucket; verified links
    contract to components, and buckets that still hold several components get another centre,
    until a round of changing centres adds no link. A round makes at most one pair per bucket member, whatever the
    size of the bucket. The texts of buckets that are then still open are joined exactly, by their rarest shingles, so every
    pair that shares a bucket and reaches the threshold is in one class.
    """
    found = _classes(located(docs), id_col, text_col, similarity, bands, rows)
    return found.select(F.col("doc").alias(id_col), "class_id", "class_size", "kept", "n_links", FILE, ROW)


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each class, with all its columns."""
    here = located(docs)
    mark = scratch_mark()
    gone = materialise(_classes(here, id_col, text_col, SIMILARITY, BANDS, ROWS).where(~F.col("kept")).select(FILE, ROW), "nd-gone")
    drop_scratch(docs.sparkSession, mark, (gone,))
    return unpacked(here.join(bounded_broadcast(gone, BROADCAST_ROWS), [FILE, ROW], "left_anti"), docs.columns)
