"""Functions for SQL: scalar, aggregate and table functions, registered under one prefix."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators import basis
from ..operators.geometry import span_of


def host_element(x: Column, lo: float, hi: float, n: int) -> Column:
    """The span of a coordinate; stays inside generated code."""
    return span_of(x, lo, hi, n)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def spline_values(x: pd.Series, n_el: pd.Series, degree: pd.Series) -> pd.Series:
    """The degree+1 spline values at points of [0, 1] with n_el spans (both constant within a batch)."""
    if not len(x):
        return pd.Series([], dtype=object)
    n, p = int(n_el.iloc[0]), int(degree.iloc[0])
    at = x.to_numpy(float)
    s = np.clip(np.floor(at * n + 1e-8).astype(int), 0, n - 1)
    return pd.Series(list(basis.spline_extracted(2 * (at * n - s) - 1, s, n, p, 1.0 / n)[0]))


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def lagrange_values(xi: pd.Series, degree: pd.Series) -> pd.Series:
    return pd.Series(list(basis.lagrange(xi.to_numpy(float), int(degree.iloc[0]))[0])) if len(xi) else pd.Series([], dtype=object)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def bernstein_values(xi: pd.Series, degree: pd.Series) -> pd.Series:
    return pd.Series(list(basis.bernstein(xi.to_numpy(float), int(degree.iloc[0]))[0])) if len(xi) else pd.Series([], dtype=object)


@F.pandas_udf(T.DoubleType())
def weighted_l2(u: pd.Series, v: pd.Series, w: pd.Series) -> float:
    """Grouped aggregate: weighted L2 norm of a difference; the expression form partially aggregates and is preferred."""
    return float(np.sqrt((w * (u - v) ** 2).sum()))


def weighted_l2_expr(u: str, v: str, w: str) -> Column:
    return F.sqrt(F.sum(F.col(w) * F.pow(F.col(u) - F.col(v), F.lit(2))))


def vec_sum(col: str, d: int) -> Column:
    """Sum of d-vectors by component, with partial aggregation."""
    return F.array(*[F.sum(F.col(col)[r]) for r in range(d)])


@F.udtf(returnType=T.StructType([T.StructField("i", T.LongType()), T.StructField("j", T.LongType())]))
class SupportPairs:
    """Pairs i <= j of an element's vertices."""

    def eval(self, vs: list) -> Iterator[tuple]:
        vs = sorted(set(vs or []))
        for a, i in enumerate(vs):
            for j in vs[a:]:
                yield i, j


@F.udtf(returnType=T.StructType([T.StructField("j", T.IntegerType())]))
class NeighbourBand:
    """Indices within p of an index, inside [0, n)."""

    def eval(self, ix: int, p: int, n: int) -> Iterator[tuple]:
        for j in range(max(0, ix - p), min(n, ix + p + 1)):
            yield (j,)


def support_pairs_expr(vs: Column) -> Column:
    """The same pairs as an array of structs, inside the JVM."""
    s = F.array_sort(F.array_distinct(vs))
    return F.flatten(F.transform(s, lambda i: F.transform(F.filter(s, lambda j: j >= i), lambda j: F.struct(i.alias("i"), j.alias("j")))))


def register(spark: SparkSession, prefix: str = "og_") -> None:
    for name, f in (("spline_values", spline_values), ("lagrange_values", lagrange_values), ("bernstein_values", bernstein_values), ("weighted_l2", weighted_l2)):
        spark.udf.register(prefix + name, f)
    spark.udtf.register(prefix + "support_pairs", SupportPairs)
    spark.udtf.register(prefix + "neighbour_band", NeighbourBand)
