"""Document quality by supervised subword embeddings.

Words, pairs of neighbouring words and character n-grams (2 to 4 characters, the blanks around a
word counting as its edges) are hashed into learned vectors; a document is the average of its
vectors; a softmax layer scores it. Vectors and layer are trained together by stochastic gradient
descent in numpy. Scoring uses that the projection of an average is the average of projections,
so each bucket needs one number, and a whole block of texts is scored by array operations.
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
from .common import held_out, text_batches, text_of

#: Bounds of the training sample (documented parameters): labelled documents, and characters of one of them.
TRAIN_DOCS = 4_000
TRAIN_DOC_CHARS = 100_000

NGRAMS = (2, 3, 4)
_MUL = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], np.uint32)
_AGAIN = 0x5BD1E995


@dataclass
class QualityModel:
    vectors: np.ndarray  # buckets x dim
    layer: np.ndarray  # dim x 2
    bias: np.ndarray  # 2

    @property
    def projected(self) -> np.ndarray:
        """What each bucket adds to the difference of the two classes' logits."""
        return (self.vectors @ (self.layer[:, 1] - self.layer[:, 0])).astype(np.float32)

    @property
    def offset(self) -> float:
        return float(self.bias[1] - self.bias[0])


def features(block: tv.Block, buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (document index, bucket), in several arrays; the same texts always give the same."""
    mask = np.uint32(buckets - 1)
    word = block.word_hashes()
    if len(word):
        yield block.w_doc, (word >> np.uint64(32)).astype(np.uint32) & mask
        same = block.w_doc[1:] == block.w_doc[:-1]
        pair = tv.mix(word[:-1] * np.uint64(3) + word[1:]) >> np.uint64(32)
        yield block.w_doc[1:][same], pair[same].astype(np.uint32) & mask
        # a pair of equal words is also hashed as "word, same again", whatever the word
        again = np.flatnonzero(same & (word[1:] == word[:-1]))
        yield block.w_doc[again + 1], np.full(len(again), _AGAIN & (buckets - 1), np.uint32)
    # a blank in front, so that the first word of a block has the same edge as any other
    blank = np.concatenate([[True], block.blank])
    codes = np.concatenate([[np.uint32(32)], np.where(block.blank, np.uint32(32), block.codes)])
    doc_of = np.repeat(np.arange(block.n), block.ends - block.starts)
    for n in NGRAMS:
        size = len(codes) - n + 1
        if size <= 0:
            continue
        h = np.full(size, n, np.uint32)
        for j in range(n):
            h = (h ^ codes[j : j + size]) * _MUL[j]
            h ^= h >> np.uint32(15)
        # a gram lies in one word, or has a blank as its first or last character
        ok = ~(blank[:size] & blank[n - 1 :])
        for j in range(1, n - 1):
            ok &= ~blank[j : j + size]
        # the second character of a gram is in the document of its word
        at = np.flatnonzero(ok)
        yield doc_of[at], h[at] & mask


def train(texts: list[str], labels: list[int], buckets: int = 1 << 18, dim: int = 12, epochs: int = 4, rate: float = 0.5, seed: int = 7) -> QualityModel:
    rng = np.random.default_rng(seed)
    model = QualityModel((rng.random((buckets, dim), np.float32) - 0.5) / dim, np.zeros((dim, 2), np.float32), np.zeros(2, np.float32))
    y = np.asarray(labels, np.int64)
    rows = []
    for t in texts:
        parts = [b for _, b in features(tv.Block([t]), buckets)]
        ids = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
        rows.append((lambda u, c: (u.astype(np.int32), (c / max(len(ids), 1)).astype(np.float32)))(*np.unique(ids, return_counts=True)))
    total, done = max(1, epochs * len(texts)), 0
    for _ in range(epochs):
        for i in rng.permutation(len(texts)):
            step = np.float32(rate * (1 - done / total))
            done += 1
            ids, share = rows[i]
            mean = share @ model.vectors[ids] if len(ids) else np.zeros(dim, np.float32)
            z = mean @ model.layer + model.bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[y[i]] -= 1.0
            back = model.layer @ p
            model.layer -= step * np.outer(mean, p)
            model.bias -= step * p
            if len(ids):
                # the vectors of a document share one gradient; long documents have small shares each
                model.vectors[ids] -= step * dim * share[:, None] * back[None, :]
    return model


def score(texts: list[str], projected: np.ndarray, offset: float) -> np.ndarray:
    """Probability of class 1 for each text."""
    total, count = np.zeros(len(texts)), np.zeros(len(texts))
    for a, b in tv.blocks(texts):
        for doc, bucket in features(tv.Block(texts[a:b]), len(projected)):
            total[a:b] += np.bincount(doc, weights=projected[bucket], minlength=b - a)
            count[a:b] += np.bincount(doc, minlength=b - a)
    return 1.0 / (1.0 + np.exp(-(total / np.maximum(count, 1) + offset)))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", max_docs: int = TRAIN_DOCS, max_chars: int = TRAIN_DOC_CHARS) -> QualityModel:
    """Train on a bounded sample of labelled rows outside the test fold, ordered by a hash of the id.

    Without usable labels the model scores 0.5 everywhere.
    """
    known = (
        labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("y"))
        .where(F.col("y").isin(0, 1) & F.col("id").isNotNull() & ~held_out("id"))
        .groupBy("id").agg(F.max("y").alias("y"))
        .orderBy(F.xxhash64("id"), "id").limit(max_docs)
    )
    got = docs.select(F.col(id_col).cast("long").alias("id"), text_of(text_col).alias("t")).where(F.length("t") <= max_chars)
    sample = got.join(F.broadcast(known), "id").groupBy("id").agg(F.min("t").alias("t"), F.max("y").alias("y")).collect()
    sample.sort(key=lambda r: r["id"])
    if not sample:
        return QualityModel(np.zeros((4, 1), np.float32), np.zeros((1, 2), np.float32), np.zeros(2, np.float32))
    model = train([r["t"] for r in sample], [r["y"] for r in sample])
    del sample
    tv.release()
    return model


def _scorer(spark, model: QualityModel):
    shared = spark.sparkContext.broadcast((model.projected, model.offset))  # one megabyte, whatever the data
    return lambda texts: score(texts, *shared.value)


def predict(docs: DataFrame, model: QualityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, held_out, score, predicted.

    Null and empty texts get the score of an average of no vectors, the bias alone. Repeated rows
    are scored alike. Only the id and text columns are read, so other names cannot clash.
    """
    scorer = _scorer(docs.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tv.pieces(batches):
            s = scorer(batch.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], ["id", "held_out", "score", "predicted"])

    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("held_out", T.BooleanType()), T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    out = text_batches(docs).select(F.col(id_col).cast("long").alias("id"), held_out(id_col).alias("held_out"), text_of(text_col).alias("text")).mapInArrow(run, schema)
    return out.withColumnRenamed("id", id_col)


def keep_good(docs: DataFrame, model: QualityModel, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """The rows that score at least ``threshold``, with all their columns as they are."""
    scorer = _scorer(docs.sparkSession, model)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tv.pieces(batches):
            s = scorer([t or "" for t in batch.column(at).to_pylist()])
            yield batch.filter(pa.array(s >= threshold))

    # columns go by place, so that any name will do
    plain = T.StructType([T.StructField(f"c{i}", f.dataType) for i, f in enumerate(docs.schema)])
    return text_batches(docs).toDF(*plain.names).mapInArrow(run, plain).toDF(*docs.columns)
