"""Language of every word in code-switched text by a linear-chain conditional random field.

A word's features are the word itself (lexicon), its affixes of 1 to 3 letters and its letter
n-grams (2 and 3, with word edges), hashed into learned weights per language; learned
transitions join neighbouring words. Forward-backward gives each word's posterior over languages,
over whole texts of any length: a text is cut into segments whose transfer matrices are
multiplied first, so that all segments of a block run side by side and the result is exact.
A document's language is the one with the largest mean posterior over its words.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textvec as tv
from .common import held_out, small_enough, text_batches, text_of

#: Bounds of the training sample (documented parameters): documents of a language, and characters of one.
TRAIN_DOCS_PER_LANG = 400
TRAIN_DOC_CHARS = 100_000
#: A column with more values than this holds no languages; the model has a weight of each bucket for each.
MAX_LANGS = 500
SEGMENT = 32
UNDETERMINED = "und"

_table: list[np.ndarray] = []


def letters() -> np.ndarray:
    """For each code point, whether it is a letter."""
    if not _table:
        _table.append(np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000))
    return _table[0]


@dataclass
class LangModel:
    langs: list[str]
    weights: np.ndarray  # buckets x languages
    transitions: np.ndarray  # languages x languages, log scale


def word_features(block: tv.Block, buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (word index, bucket), in several arrays with rising word index each."""
    mask = np.uint64(buckets - 1)
    n = len(block.w_start)
    sums = block.prefix_sums()
    every = np.arange(n)
    size = block.w_end - block.w_start
    word = block.spans_hash(sums, block.w_start, block.w_end)
    yield every, (tv.mix(word + np.uint64(1)) & mask).astype(np.int64)
    for k in (1, 2, 3):
        at = np.flatnonzero(size >= k)
        for kind, lo in ((10, block.w_start[at]), (20, block.w_end[at] - k)):
            h = block.spans_hash(sums, lo, lo + k)
            yield at, (tv.mix(h + np.uint64(kind + k)) & mask).astype(np.int64)
    # the word of a letter
    owner = np.cumsum(np.concatenate([[True], block.blank[:-1]]) & ~block.blank) - 1
    # a blank in front, so that the first word of a block has the same edge as any other
    blank = np.concatenate([[True], block.blank])
    codes = np.concatenate([[np.uint32(0)], np.where(block.blank, np.uint32(0), block.codes)])
    for g in (2, 3):
        m = len(codes) - g + 1
        if m <= 0:
            continue
        h = np.full(m, 0x9E3779B1 + g, np.uint32)
        for j in range(g):
            h = (h ^ codes[j : j + m]) * np.uint32(0x85EBCA77)
            h ^= h >> np.uint32(13)
        ok = ~(blank[:m] & blank[g - 1 :])
        for j in range(1, g - 1):
            ok &= ~blank[j : j + m]
        at = np.flatnonzero(ok)
        yield owner[at - 1 + blank[at]], (h[at] & np.uint32(buckets - 1)).astype(np.int64)


def emissions(block: tv.Block, weights: np.ndarray) -> np.ndarray:
    n, k = len(block.w_start), weights.shape[1]
    out = np.zeros((n, k))
    for word, bucket in word_features(block, len(weights)):
        got = weights[bucket]
        for c in range(k):
            out[:, c] += np.bincount(word, weights=got[:, c], minlength=n)
    return out


def posteriors(emit: np.ndarray, doc: np.ndarray, transitions: np.ndarray, segment: int = SEGMENT) -> np.ndarray:
    """Exact posterior of each word; ``doc`` is rising, and chains do not cross its borders."""
    n, k = emit.shape
    if not n:
        return emit
    psi = np.exp(emit - emit.max(axis=1, keepdims=True))
    trans = np.exp(transitions)
    docs, first, length = np.unique(doc, return_index=True, return_counts=True)
    n_seg = -(-length // segment)
    seg_rank = np.arange(n_seg.sum()) - np.repeat(np.cumsum(n_seg) - n_seg, n_seg)
    seg_from = np.repeat(first, n_seg) + seg_rank * segment
    seg_len = np.minimum(np.repeat(first + length, n_seg) - seg_from, segment)
    steps = int(seg_len.max())
    move = np.tile(np.eye(k), (len(seg_from), 1, 1))
    for s in range(steps):
        on = np.flatnonzero(seg_len > s)
        at = seg_from[on] + s
        start = (seg_rank[on] == 0) & (s == 0)
        new = move[on] @ trans
        if start.any():
            new[start] = move[on[start]]
        new *= psi[at][:, None, :]
        move[on] = new / new.max(axis=(1, 2), keepdims=True)
    # across segments: one step for each rank, all documents side by side
    into, outof = np.ones((len(seg_from), k)), np.ones((len(seg_from), k))
    by_rank = np.argsort(seg_rank, kind="stable")
    cuts = np.cumsum(np.bincount(seg_rank))[:-1]
    ranks = np.split(by_rank, cuts)
    for here in ranks[1:]:
        v = np.einsum("ij,ijk->ik", into[here - 1], move[here - 1])
        into[here] = v / v.max(axis=1, keepdims=True)
    for here in ranks[:0:-1]:
        v = np.einsum("ijk,ik->ij", move[here], outof[here])
        outof[here - 1] = v / v.max(axis=1, keepdims=True)
    fore, back = np.empty((n, k)), np.empty((n, k))
    state = into.copy()
    for s in range(steps):
        on = np.flatnonzero(seg_len > s)
        at = seg_from[on] + s
        new = state[on] @ trans
        start = (seg_rank[on] == 0) & (s == 0)
        new[start] = 1.0
        new *= psi[at]
        new /= new.max(axis=1, keepdims=True)
        state[on] = fore[at] = new
    state = outof.copy()
    for s in range(steps - 1, -1, -1):
        on = np.flatnonzero(seg_len > s)
        at = seg_from[on] + s
        back[at] = state[on]
        new = (psi[at] * state[on]) @ trans.T
        state[on] = new / new.max(axis=1, keepdims=True)
    out = fore * back
    return out / out.sum(axis=1, keepdims=True)


def pair_expectations(emit: np.ndarray, doc: np.ndarray, transitions: np.ndarray, post: np.ndarray) -> np.ndarray:
    """Expected numbers of transitions between neighbouring words of a document, for training.

    Sequences are short here, so plain forward and backward passes over padded rows serve.
    """
    k = emit.shape[1]
    same = np.flatnonzero(doc[1:] == doc[:-1])
    psi, trans = np.exp(emit - emit.max(axis=1, keepdims=True)), np.exp(transitions)
    fore, back = _plain_passes(psi, doc, trans)
    joint = fore[same][:, :, None] * trans[None] * (psi[same + 1] * back[same + 1])[:, None, :]
    return (joint / joint.sum(axis=(1, 2), keepdims=True)).sum(axis=0) if len(same) else np.zeros((k, k))


def _plain_passes(psi: np.ndarray, doc: np.ndarray, trans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    n, k = psi.shape
    _, first, length = np.unique(doc, return_index=True, return_counts=True)
    fore, back = np.empty((n, k)), np.ones((n, k))
    for s in range(int(length.max(initial=0))):
        at = first[length > s] + s
        new = psi[at] if s == 0 else (fore[at - 1] @ trans) * psi[at]
        fore[at] = new / new.max(axis=1, keepdims=True)
    for s in range(int(length.max(initial=0)) - 2, -1, -1):
        at = first[length > s + 1] + s
        new = (psi[at + 1] * back[at + 1]) @ trans.T
        back[at] = new / new.max(axis=1, keepdims=True)
    return fore, back


def train(texts: list[str], langs: list[str], buckets: int = 1 << 17, window: int = 40, windows: int = 3, epochs: int = 3, rate: float = 0.3, seed: int = 11) -> LangModel:
    """Stochastic gradient ascent (with per-weight step sizes) on the likelihood of windows of words.

    Half of the windows join pieces of documents of different languages, so that transitions see switches.
    """
    names = sorted(set(langs))
    k = len(names)
    if not k:
        return LangModel([], np.zeros((buckets, 0), np.float32), np.zeros((0, 0)))
    rng = np.random.default_rng(seed)
    pieces: list[tuple[str, int]] = []
    for text, lang in zip(texts, langs, strict=True):
        block = tv.Block([text.lower()], letters())
        n = len(block.w_start)
        for _ in range(windows if n else 0):
            size = max(1, window // 2)
            at = int(rng.integers(0, max(1, n - size + 1)))
            end = min(n, at + size)
            low = text.lower()
            pieces.append((low[block.w_start[at] : block.w_end[end - 1]], names.index(lang)))
    order = rng.permutation(len(pieces))
    sequences = [[pieces[i] for i in order[j : j + 2]] for j in range(0, len(order), 2)]
    weights, trans = np.zeros((buckets, k), np.float32), np.zeros((k, k))
    seen, seen_t = np.full((buckets, k), 1e-6, np.float32), np.full((k, k), 1e-6)
    for _ in range(epochs):
        rng.shuffle(sequences)
        for j in range(0, len(sequences), 64):
            batch = sequences[j : j + 64]
            flat = [p for seq in batch for p in seq]
            block = tv.Block([p[0] for p in flat], letters())
            gold = np.array([p[1] for p in flat])[block.w_doc]
            owner = np.repeat(np.arange(len(batch)), [len(s) for s in batch])[block.w_doc]
            if not len(gold):
                continue
            parts = list(word_features(block, buckets))
            word, bucket = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
            emit = np.stack([np.bincount(word, weights=weights[bucket, c], minlength=len(gold)) for c in range(k)], axis=1)
            post = posteriors(emit, owner, trans)
            slope = -post
            slope[np.arange(len(gold)), gold] += 1.0
            ids, back = np.unique(bucket, return_inverse=True)
            grad = np.stack([np.bincount(back, weights=slope[word, c], minlength=len(ids)) for c in range(k)], axis=1) / len(batch)
            seen[ids] += grad.astype(np.float32) ** 2
            weights[ids] += (rate * grad / np.sqrt(seen[ids])).astype(np.float32) * 0.1
            same = np.flatnonzero(owner[1:] == owner[:-1])
            real = np.zeros((k, k))
            np.add.at(real, (gold[same], gold[same + 1]), 1.0)
            gt = (real - pair_expectations(emit, owner, trans, post)) / len(batch)
            seen_t += gt**2
            trans += rate * gt / np.sqrt(seen_t)
    return LangModel(names, weights, trans)


def label_block(texts: list[str], model: LangModel) -> tuple[tv.Block, np.ndarray]:
    block = tv.Block([t.lower() for t in texts], letters())
    emit = emissions(block, model.weights)
    return block, posteriors(emit, block.w_doc, model.transitions)


def label_words(text: str, model: LangModel) -> list[tuple[str, str, float]]:
    """(word, language, posterior) of every word of a text."""
    block, post = label_block([text], model)
    low = text.lower()
    best = post.argmax(axis=1)
    return [(low[a:b], model.langs[c], float(p[c])) for a, b, c, p in zip(block.w_start, block.w_end, best, post, strict=True)]


def predict_texts(texts: list[str], model: LangModel) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(language, score, number of switches) of each text."""
    names, scores, switches = [], np.zeros(len(texts)), np.zeros(len(texts), np.int64)
    k = len(model.langs)
    for a, b in tv.blocks(texts):
        if not k:
            names += [UNDETERMINED] * (b - a)
            continue
        block, post = label_block(texts[a:b], model)
        count = np.bincount(block.w_doc, minlength=b - a)
        mean = np.stack([np.bincount(block.w_doc, weights=post[:, c], minlength=b - a) for c in range(k)], axis=1) / np.maximum(count, 1)[:, None]
        best = mean.argmax(axis=1)
        names += [model.langs[c] if n else UNDETERMINED for c, n in zip(best, count, strict=True)]
        scores[a:b] = np.where(count > 0, np.clip(mean.max(axis=1), 0.0, 1.0), 0.0)
        word = post.argmax(axis=1)
        turn = (word[1:] != word[:-1]) & (block.w_doc[1:] == block.w_doc[:-1])
        switches[a:b] = np.bincount(block.w_doc[1:][turn], minlength=b - a)
    return names, scores, switches


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_lang: int = TRAIN_DOCS_PER_LANG, max_chars: int = TRAIN_DOC_CHARS) -> LangModel:
    """Train on a bounded sample of documents with a language, outside the test fold, by a hash of the id.

    More than ``MAX_LANGS`` languages are an error: a sample of each is collected.
    """
    spark = docs.sparkSession
    known = docs.select(F.col(id_col).cast("long").alias("id"), F.col(lang_col).alias("lang"), F.length(text_of(text_col)).alias("n")).where(
        F.col("lang").isNotNull() & F.col("id").isNotNull() & ~held_out("id") & F.col("n").between(1, max_chars)
    )
    # a hash threshold per language draws a little more than is wanted, whatever the size of a language
    counts = known.groupBy("lang").agg(F.count(F.lit(1)).alias("c"))
    if not small_enough(counts, MAX_LANGS):
        raise ValueError(f"more than {MAX_LANGS} languages")
    share = F.least(F.lit(1.0), F.lit(1.3 * per_lang + 50) / F.col("c"))
    place = F.pmod(F.xxhash64("id"), F.lit(1 << 40))
    drawn = known.join(F.broadcast(counts), "lang").where(place < share * float(1 << 40)).select("id", "lang", place.alias("place")).distinct().collect()
    chosen: list[tuple] = []
    taken: dict[str, int] = {}
    for r in sorted(drawn, key=lambda r: (r["lang"], r["place"], r["id"])):
        taken[r["lang"]] = taken.get(r["lang"], 0) + 1
        if taken[r["lang"]] <= per_lang:
            chosen.append((r["id"], r["lang"]))
    if not chosen:
        return train([], [])
    few = spark.createDataFrame(chosen, "id long, lang string")
    got = docs.select(F.col(id_col).cast("long").alias("id"), F.col(lang_col).alias("lang"), text_of(text_col).alias("t"))
    rows = got.join(F.broadcast(few), ["id", "lang"]).groupBy("id", "lang").agg(F.min("t").alias("t")).collect()
    rows.sort(key=lambda r: (r["id"], r["lang"]))
    model = train([r["t"] for r in rows], [r["lang"] for r in rows])
    del rows
    tv.release()
    return model


def predict(docs: DataFrame, model: LangModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, held_out, lang_pred, score, switches.

    ``lang_pred`` is ``und`` with score 0 where the text is null or has no letter. Ties go to
    the first language by name. Only the id and text columns are read, so other names cannot clash.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # fixed size: buckets x languages

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tv.pieces(batches):
            names, scores, switches = predict_texts(batch.column(2).to_pylist(), shared.value)
            cols = [batch.column(0), batch.column(1), pa.array(names, pa.string()), pa.array(scores), pa.array(switches)]
            yield pa.RecordBatch.from_arrays(cols, ["id", "held_out", "lang_pred", "score", "switches"])

    schema = T.StructType(
        [T.StructField("id", T.LongType()), T.StructField("held_out", T.BooleanType()), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("switches", T.LongType())]
    )
    out = text_batches(docs).select(F.col(id_col).cast("long").alias("id"), held_out(id_col).alias("held_out"), text_of(text_col).alias("text")).mapInArrow(run, schema)
    return out.withColumnRenamed("id", id_col)
