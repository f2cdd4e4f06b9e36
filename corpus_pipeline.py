"""The corpus pipeline: good documents, each text once, mixed to target weights, as token ids.

Every stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept. ``run``
writes each stage as Parquet in the shared folder, reads it back for the next one, and drops the stage's own scratch tables.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from overlapgraph.llm import bpe, exact_dedup, mixing, probminhash, quality
from overlapgraph.llm.common import drop_scratch, materialise, read_table, scratch_mark
from overlapgraph.llm.queries import bpe_path


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; it learns from the labels of these documents."""
    return quality.keep_good(docs, quality.fit(docs, read_table(spark, sf_dir, "labels")))


def drop_exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the smallest id stays."""
    return exact_dedup.drop_copies(docs)


def drop_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near-duplicates the row with the smallest id stays."""
    return probminhash.drop_near_copies(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return mixing.emit(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The token ids of every row of the mix."""
    return bpe.encode(docs, bpe_path())


STAGES = [
    ("quality classifier", keep_quality),
    ("exact dedup", drop_exact),
    ("near-duplicate removal", drop_near),
    ("mixing to target weights", mix_sources),
    ("BPE encoding and decoding", encode),
]

#: The classifier and the sketches cannot be said in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        mark = scratch_mark()
        docs = materialise(stage(spark, docs, sf_dir), "pipeline-" + name.split(" ")[0])
        drop_scratch(spark, mark, (docs,))
    return STAGES[-1][1](spark, docs, sf_dir)
