"""Connected components by repeated contraction to the smallest neighbour."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_broadcast, drop_scratch, materialise, scratch_mark

#: Up to this many labels (16 bytes each) are broadcast; beyond, the joins shuffle and AQE splits hot keys.
BROADCAST_LABELS = 500_000


def _to_roots(move: DataFrame) -> DataFrame:
    """Pointers (v, m) with m <= v to pointers that end at a fixed point: each step doubles what a vertex has seen."""
    while True:
        up = bounded_broadcast(move, BROADCAST_LABELS).select(F.col("v").alias("m"), F.col("m").alias("far"))
        step = materialise(move.join(up, "m", "left").select("v", F.coalesce("far", "m").alias("m"), (F.coalesce("far", "m") != F.col("m")).alias("moved")), "cc-jump")
        move = step.select("v", "m")
        if step.where("moved").isEmpty():
            return move


def components(links: DataFrame) -> DataFrame:
    """Links (a, b) of 64-bit vertices to rows (v, root), for the vertices that have a link.

    In each round every vertex points to its smallest neighbour, if that is smaller; the pointers are followed
    to their ends by doubling, and the links are contracted. A vertex that ends a round is smaller than its
    neighbours; after two rounds at most half of the vertices are left: one that nobody pointed to has a smaller neighbour
    in the second. So the rounds, and the doublings in each, grow with the logarithm of the number of vertices, for
    chains as for stars. Every table stays distributed. The root is the smallest vertex of a component.
    """
    mark = scratch_mark()
    edges = materialise(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "cc-edges")
    label = None
    while True:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        move = materialise(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("v"), F.least("a", "m").alias("m")), "cc-move")
        move = _to_roots(move)
        small = bounded_broadcast(move, BROADCAST_LABELS)
        if label is None:
            label = move.select("v", F.col("m").alias("root"))
        else:
            to = small.select(F.col("v").alias("root"), "m")
            label = label.join(to, "root", "left").select("v", F.coalesce("m", "root").alias("root"))
        label = materialise(label, "cc-label")
        end_a = small.select(F.col("v").alias("a"), F.col("m").alias("ma"))
        end_b = small.select(F.col("v").alias("b"), F.col("m").alias("mb"))
        edges = materialise(
            edges.join(end_a, "a").join(end_b, "b").where("ma <> mb").select(F.greatest("ma", "mb").alias("a"), F.least("ma", "mb").alias("b")).distinct(),
            "cc-edges",
        )
        if edges.isEmpty():
            drop_scratch(links.sparkSession, mark, (label,))
            return label
