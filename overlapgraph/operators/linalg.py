"""Vector kernels on partitioned data: linear combination, dot product, sparse product."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def lincomb(a: float, x: DataFrame, b: float, y: DataFrame) -> DataFrame:
    """a x + b y, both (v, x) with scalars or arrays; no value of another vertex is needed."""
    both = x.select("v", F.col("x").alias("p")).join(y.select("v", F.col("x").alias("q")), "v")
    if x.schema["x"].dataType.simpleString().startswith("array"):
        return both.select("v", F.zip_with("p", "q", lambda p, q: p * a + q * b).alias("x"))
    return both.select("v", (F.col("p") * a + F.col("q") * b).alias("x"))


def _inner(p: Column, q: Column, is_array: bool) -> Column:
    return F.aggregate(F.zip_with(p, q, lambda s, t: s * t), F.lit(0.0), lambda s, t: s + t) if is_array else p * q


def dot_parts(x: DataFrame, y: DataFrame, part: DataFrame) -> DataFrame:
    """Rows (k, dot): each part's share over its core vertices; their sum is the dot product."""
    is_array = x.schema["x"].dataType.simpleString().startswith("array")
    both = x.select("v", F.col("x").alias("p")).join(y.select("v", F.col("x").alias("q")), "v").join(part, "v")
    return both.groupBy("k").agg(F.sum(_inner(F.col("p"), F.col("q"), is_array)).alias("dot"))


def dot(x: DataFrame, y: DataFrame) -> float:
    is_array = x.schema["x"].dataType.simpleString().startswith("array")
    both = x.select("v", F.col("x").alias("p")).join(y.select("v", F.col("x").alias("q")), "v")
    return both.agg(F.coalesce(F.sum(_inner(F.col("p"), F.col("q"), is_array)), F.lit(0.0))).first()[0]


def norm2(x: DataFrame) -> float:
    return dot(x, x) ** 0.5


def refresh_halo(x: DataFrame, part: DataFrame, comm: DataFrame) -> DataFrame:
    """Rows (k, v, x): core values of each part and copies of its halo values; only the copies move."""
    own = x.join(part, "v").select("k", "v", "x")
    copies = comm.select(F.col("k_to").alias("k"), "v").join(x, "v").select("k", "v", "x")
    return own.unionByName(copies)


def _apply(val: Column, x: Column, d: int) -> Column:
    """A d x d block, stored row by row, times a d-vector."""
    return F.array(*[reduce(lambda a, b: a + b, [val[r * d + c] * x[c] for c in range(d)]) for r in range(d)])


def _sum(col: Column, d: int) -> Column:
    return F.sum(col) if d == 1 else F.array(*[F.sum(col[r]) for r in range(d)])


def place_parts(kp: DataFrame, n_dom: int) -> DataFrame:
    """Part-owned rows (k, i, j, val) where their part is, once for all products: one partition per part number, on disk.

    A lost copy is made again from the table behind it. Give the space back with ``unpersist``.
    """
    return kp.select("k", "i", "j", "val").repartition(n_dom, "k").sortWithinPartitions("k").persist(StorageLevel.DISK_ONLY)


def spmv_parts(kp: DataFrame, x: DataFrame, part: DataFrame, comm: DataFrame, d: int = 1) -> DataFrame:
    """Rows (k, v, x) of the product: part-owned rows (k, i, j, val) times core and halo values.

    A part's rows meet its values in one task. With rows from ``place_parts`` only the values of the vector move.
    """
    local = refresh_halo(x, part, comm).select(F.col("k").alias("at"), F.col("v").alias("j"), "x")
    out = "double" if d == 1 else "array<double>"

    def run(rows: pa.Table, values: pa.Table) -> pa.Table:
        def numbers(col: pa.ChunkedArray, shape: tuple) -> np.ndarray:
            flat = col.combine_chunks()
            return (flat if d == 1 else flat.flatten()).to_numpy(zero_copy_only=False).reshape(shape)

        ids = values["j"].to_numpy()
        order = np.argsort(ids, kind="stable")
        at = np.searchsorted(ids[order], rows["j"].to_numpy())
        have = at < len(ids)
        have[have] = ids[order][at[have]] == rows["j"].to_numpy()[have]
        xs, val = numbers(values["x"], (-1, d)), numbers(rows["val"], (-1, d, d))
        v, place = np.unique(rows["i"].to_numpy()[have], return_inverse=True)
        y = np.einsum("nrc,nc->nr", val[have], xs[order[at[have]]])
        total = np.stack([np.bincount(place, weights=y[:, r], minlength=len(v)) for r in range(d)], 1)
        got = pa.array(total[:, 0]) if d == 1 else pa.ListArray.from_arrays(np.arange(0, total.size + 1, d, dtype=np.int32), pa.array(total.reshape(-1)))
        k = rows["k"][0].as_py() if len(rows) else 0
        return pa.table({"k": pa.array(np.full(len(v), k, np.int32)), "v": pa.array(v), "x": got})

    return kp.groupBy("k").cogroup(local.groupBy("at")).applyInArrow(run, f"k int, v long, x {out}")


def spmv(k: DataFrame, x: DataFrame, d: int = 1) -> DataFrame:
    """Baseline: the product without a partition; every entry is shuffled to its column and to its row."""
    prod = F.col("val") * F.col("x") if d == 1 else _apply(F.col("val"), F.col("x"), d)
    return k.join(x.select(F.col("v").alias("j"), "x"), "j").withColumn("y", prod).groupBy(F.col("i").alias("v")).agg(_sum(F.col("y"), d).alias("x"))


def owned_rows(k: DataFrame, part: DataFrame) -> DataFrame:
    return k.join(part.select(F.col("v").alias("i"), "k"), "i").select("k", "i", "j", "val")


def split_blocks(kp: DataFrame, part: DataFrame) -> DataFrame:
    """Entries with ``inner``: whether the column is core (local data) or halo (received)."""
    return kp.join(part.select(F.col("v").alias("j"), F.col("k").alias("kj")), "j").select("k", "i", "j", "val", (F.col("k") == F.col("kj")).alias("inner"))


def residual(k: DataFrame, x: DataFrame, f: DataFrame) -> DataFrame:
    return lincomb(1.0, f, -1.0, spmv(k, x))
