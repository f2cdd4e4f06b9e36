"""One-dimensional bases and their tensor products, in numpy and as SQL expressions."""

from __future__ import annotations

from functools import lru_cache
from math import comb

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .meshes import MeshSpec, open_knots


def lagrange(xi: np.ndarray, p: int) -> tuple[np.ndarray, np.ndarray]:
    """Values and derivatives of the p+1 Lagrange polynomials at points of [-1, 1]."""
    nodes = np.linspace(-1.0, 1.0, p + 1)
    xi = np.asarray(xi, float)[..., None]
    val, der = [], []
    for a in range(p + 1):
        others = np.delete(nodes, a)
        scale = np.prod(nodes[a] - others)
        diff = xi - others
        val.append(np.prod(diff, axis=-1) / scale)
        der.append(sum(np.prod(np.delete(diff, m, axis=-1), axis=-1) for m in range(p)) / scale)
    return np.stack(val, -1), np.stack(der, -1)


def bernstein(xi: np.ndarray, p: int) -> tuple[np.ndarray, np.ndarray]:
    """Values and derivatives of the p+1 Bernstein polynomials at points of [-1, 1]."""
    t = (np.asarray(xi, float)[..., None] + 1) / 2
    poly = lambda q: np.concatenate([comb(q, a) * t**a * (1 - t) ** (q - a) for a in range(q + 1)], -1)
    val = poly(p)
    if p == 0:
        return val, np.zeros_like(val)
    low = poly(p - 1)
    zero = np.zeros_like(t)
    return val, p / 2 * (np.concatenate([zero, low], -1) - np.concatenate([low, zero], -1))


@lru_cache
def extraction_operators(n_el: int, p: int) -> np.ndarray:
    """For each span of an open uniform knot vector, the matrix that maps Bernstein to spline values.

    The matrices come from the coefficients of both bases at p+1 points of a span: the splines
    there by recursion, the Bernstein polynomials by formula; both span the same polynomials.
    """
    knots = np.array(open_knots(0.0, float(n_el), n_el, p))
    at = (np.arange(p + 1) + 0.5) / (p + 1)
    bern = bernstein(2 * at - 1, p)[0]
    out = np.empty((n_el, p + 1, p + 1))
    for s in range(n_el):
        out[s] = np.linalg.solve(bern, spline_recursive(s + at, knots, p, np.full(p + 1, s))[0]).T
    out[np.abs(out) < 1e-14] = 0.0
    return out


def spline_recursive(x: np.ndarray, knots: np.ndarray, p: int, span: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values and derivatives of the p+1 splines that live on each point's span, by recursion on knots."""
    x, s = np.asarray(x, float), np.asarray(span) + p
    low = np.ones((len(x), 1))
    val = low
    for d in range(1, p + 1):
        low, val = val, np.zeros((len(x), d + 1))
        for r in range(d):
            left, right = knots[s + r + 1 - d], knots[s + r + 1]
            share = low[:, r] / (right - left)
            val[:, r] += (right - x) * share
            val[:, r + 1] += (x - left) * share
    der = np.zeros((len(x), p + 1))
    if p:
        for r in range(p):
            share = p * low[:, r] / (knots[s + r + 1] - knots[s + r + 1 - p])
            der[:, r] -= share
            der[:, r + 1] += share
    return val, der


def spline_extracted(xi: np.ndarray, span: np.ndarray, n_el: int, p: int, h: float) -> tuple[np.ndarray, np.ndarray]:
    """Values and physical derivatives of the splines of a span at reference points of [-1, 1]."""
    c = extraction_operators(n_el, p)[span]
    b, d = bernstein(xi, p)
    return np.einsum("nij,nj->ni", c, b), np.einsum("nij,nj->ni", c, d) * 2 / h


def axis_values(spec: MeshSpec, axis: int, x: np.ndarray, span: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values and derivatives, along one axis, of the functions that live on each point's span."""
    h = spec.h[axis]
    xi = 2 * ((np.asarray(x) - spec.lo[axis]) / h - span) - 1
    if spec.family == "spline":
        return spline_extracted(xi, span, spec.n_el[axis], spec.degree, h)
    val, der = lagrange(xi, spec.degree)
    return val, der * 2 / h


def tensor(values: list[np.ndarray], slopes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Products over axes, first axis fastest: (points, functions) and gradients (points, functions, dim)."""

    def outer(parts: list[np.ndarray]) -> np.ndarray:
        out = parts[0]
        for p in parts[1:]:
            out = (p[:, :, None] * out[:, None, :]).reshape(len(out), -1)
        return out

    n = outer(values)
    g = np.stack([outer([slopes[a] if a == d else values[a] for a in range(len(values))]) for d in range(len(values))], -1)
    return n, g


# ---- the same as SQL expressions ----------------------------------------------------------


def lagrange_expr(xi: Column, p: int) -> list[Column]:
    nodes = [-1.0 + 2.0 * a / p for a in range(p + 1)] if p else [0.0]
    out = []
    for a in range(p + 1):
        c = F.lit(1.0)
        for b in range(p + 1):
            if b != a:
                c = c * (xi - nodes[b]) / (nodes[a] - nodes[b])
        out.append(c)
    return out


def bernstein_expr(xi: Column, p: int) -> list[Column]:
    t = (xi + 1) / 2
    return [F.lit(float(comb(p, a))) * F.pow(t, F.lit(a)) * F.pow(1 - t, F.lit(p - a)) for a in range(p + 1)]


def extraction_table(spark: SparkSession, n_el: int, p: int) -> DataFrame:
    """Rows (span, c): a table of n_el small matrices of one axis, small enough for a broadcast at any mesh size."""
    return spark.createDataFrame([(s, m.tolist()) for s, m in enumerate(extraction_operators(n_el, p))], "span int, c array<array<double>>")


def spline_expr(xi: Column, c: Column, p: int) -> Column:
    """Array of the p+1 spline values: extraction matrix times Bernstein values."""
    b = F.array(*bernstein_expr(xi, p))
    return F.transform(c, lambda row: F.aggregate(F.zip_with(row, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x))
