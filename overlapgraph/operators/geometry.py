"""Quadrature, the geometric database, host-element search and the coupling map."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from . import basis
from .meshes import MeshSpec, digits, encode

#: A point within this distance of a span's face belongs to the upper span; an overlap must be longer.
TOLERANCE = 1e-8


def gauss_points(n: int) -> tuple[list[float], list[float]]:
    x, w = np.polynomial.legendre.leggauss(n)
    return x.tolist(), w.tolist()


def gauss_rule(spark: SparkSession, n: int, dim: int) -> DataFrame:
    """Rows (q, xi, w) of the tensor rule: n^dim of them, whatever the mesh, so a broadcast is safe."""
    x, w = gauss_points(n)
    rows = []
    for q in range(n**dim):
        i = [q // n**a % n for a in range(dim)]
        rows.append((q, [x[j] for j in i], float(np.prod([w[j] for j in i]))))
    return spark.createDataFrame(rows, "q int, xi array<double>, w double")


def quadrature(spark: SparkSession, spec: MeshSpec, n: int) -> DataFrame:
    """Rows (e, q, ie, xi, x, w): the integration points of every element, weights with the Jacobian."""
    ie = digits("e", spec.n_el)
    detj = float(np.prod([h / 2 for h in spec.h]))
    base = spark.range(spec.n_elements).withColumnRenamed("id", "e").crossJoin(F.broadcast(gauss_rule(spark, n, spec.dim)))
    x = [F.lit(spec.lo[a]) + (ie[a] + (F.col("xi")[a] + 1) / 2) * spec.h[a] for a in range(spec.dim)]
    return base.select("e", "q", F.array(*ie).alias("ie"), "xi", F.array(*x).alias("x"), (F.col("w") * detj).alias("w"))


def empirical_points(df: DataFrame, coords: list[Column], weight: Column | None = None, *keep: str) -> DataFrame:
    """Rows of a table as integration points: (x, w, kept columns)."""
    return df.select(F.array(*coords).alias("x"), (F.lit(1.0) if weight is None else weight).alias("w"), *keep)


def span_of(x: Column, lo: float, hi: float, n: int, tol: float = TOLERANCE) -> Column:
    """The span of a coordinate in constant time; faces go to the upper span, the end to the last."""
    return F.greatest(F.lit(0), F.least(F.lit(n - 1), F.floor((x - lo) / ((hi - lo) / n) + tol))).cast("int")


def locate_bucket(points: DataFrame, spec: MeshSpec, x: str = "x", tol: float = TOLERANCE) -> DataFrame:
    """Adds the host element's number ``e_g`` and multi-index ``ie_g``: a projection, no join."""
    ie = [span_of(F.col(x)[a], spec.lo[a], spec.hi[a], spec.n_el[a], tol) for a in range(spec.dim)]
    return points.withColumn("e_g", encode(ie, spec.n_el)).withColumn("ie_g", F.array(*ie))


def locate_tree(points: DataFrame, spec: MeshSpec, x: str = "x", tol: float = TOLERANCE) -> DataFrame:
    """Baseline: bisection on the sorted span faces of each axis, for any spacing of the faces."""
    faces = [[spec.lo[a] + i * spec.h[a] for i in range(spec.n_el[a] + 1)] for a in range(spec.dim)]
    schema = T.StructType([*points.schema.fields, T.StructField("e_g", T.LongType())])

    def run(batches):
        for batch in batches:
            at = batch.column(batch.schema.get_field_index(x)).flatten().to_numpy(zero_copy_only=False).reshape(-1, len(faces))
            e, stride = np.zeros(len(at), np.int64), 1
            for a, f in enumerate(faces):
                i = np.searchsorted(np.array(f) - tol * (f[1] - f[0]), at[:, a], side="right") - 1
                e += np.clip(i, 0, len(f) - 2) * stride
                stride *= len(f) - 1
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(e)], [*batch.schema.names, "e_g"])

    return points.mapInArrow(run, schema)


def boxes(spark: SparkSession, spec: MeshSpec) -> DataFrame:
    """Rows (e_g, lo, hi) of all elements."""
    ie = digits("id", spec.n_el)
    return spark.range(spec.n_elements).select(
        F.col("id").alias("e_g"),
        F.array(*[F.lit(spec.lo[a]) + c * spec.h[a] for a, c in enumerate(ie)]).alias("lo"),
        F.array(*[F.lit(spec.lo[a]) + (c + 1) * spec.h[a] for a, c in enumerate(ie)]).alias("hi"),
    )


def locate_range(points: DataFrame, elements: DataFrame, spec: MeshSpec, bins: int, x: str = "x", tol: float = TOLERANCE) -> DataFrame:
    """Baseline for boxes of any size: an equi-join on coarse bins of the first axis, then the exact test.

    A box is copied to the bins it meets; a point is in one bin, so the join neither misses nor repeats a hit.
    """
    width = (spec.hi[0] - spec.lo[0]) / bins
    to_bin = lambda c: F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor((c - spec.lo[0]) / width))).cast("int")
    copied = elements.withColumn("bin", F.explode(F.sequence(to_bin(F.col("lo")[0] - tol), to_bin(F.col("hi")[0] + tol))))
    tests = []
    for a in range(spec.dim):
        t = tol * spec.h[a]
        c, lo, hi = F.col(x)[a], F.col("lo")[a], F.col("hi")[a]
        last = hi >= spec.hi[a] - t
        tests.append((c >= lo - t) & ((c < hi - t) | last))
    return points.withColumn("bin", to_bin(F.col(x)[0])).join(copied, "bin").where(reduce(lambda p, q: p & q, tests)).drop("bin", "lo", "hi")


#: Knots that one broadcast may hold (8 bytes each).
KNOTS = 1_000_000


def locate_asof(points: DataFrame, knots: DataFrame, by: str = "t") -> DataFrame:
    """The last knot at or before each point, for unequal knots of one axis; null before the first.

    Knots describe a mesh, so their table usually fits a broadcast at any data size: its size is checked, it is sorted once, and
    each point finds its place by bisection, without a shuffle. More than ``KNOTS`` are an error that names the window form.
    """
    if knots.limit(KNOTS + 1).count() > KNOTS:
        raise ValueError(f"more than {KNOTS} knots: use locate_asof_window with a column that cuts the axis")
    kind = points.schema[by].dataType
    sorted_ = sorted(r[0] for r in knots.select(by).distinct().collect() if r[0] is not None)  # checked size
    shared = points.sparkSession.sparkContext.broadcast(pa.array(sorted_, to_arrow_type(kind)))
    schema = T.StructType([*points.schema.fields, T.StructField("knot", kind)])

    def run(batches):
        ks = shared.value
        plain = ks.cast(pa.int64()).to_numpy() if pa.types.is_temporal(ks.type) else ks.to_numpy()
        for b in batches:
            col = b.column(b.schema.get_field_index(by))
            told = col.cast(ks.type)
            at = (told.cast(pa.int64()) if pa.types.is_temporal(ks.type) else told).to_numpy(zero_copy_only=False)
            place = np.searchsorted(plain, at, side="right") - 1
            found = ks.take(pa.array(np.maximum(place, 0), mask=(place < 0) | told.is_null().to_numpy(zero_copy_only=False)))
            yield pa.RecordBatch.from_arrays([*b.columns, found], [*b.schema.names, "knot"])

    return points.mapInArrow(run, schema)


def locate_asof_window(points: DataFrame, knots: DataFrame, part: str, by: str = "t") -> DataFrame:
    """The same for knot tables of any size, each partition of ``part`` being sorted once."""
    both = points.withColumn("k", F.lit(None).cast(points.schema[by].dataType)).withColumn("is_knot", F.lit(0)).unionByName(
        knots.select(part, by, F.col(by).alias("k"), F.lit(1).alias("is_knot")), allowMissingColumns=True
    )
    w = Window.partitionBy(part).orderBy(by, F.desc("is_knot")).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("knot", F.last("k", ignorenulls=True).over(w)).where("is_knot = 0").drop("k", "is_knot")


def _tables(spec: MeshSpec, points: np.ndarray, ie: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    parts = [basis.axis_values(spec, a, points[:, a], ie[:, a]) for a in range(spec.dim)]
    return basis.tensor([p[0] for p in parts], [p[1] for p in parts])


def geometric_database(spark: SparkSession, spec: MeshSpec, n: int) -> DataFrame:
    """Rows (e, q, x, w, n, g): values and physical gradients of the element's functions at each point."""
    schema = "e long, q int, x array<double>, w double, n array<double>, g array<array<double>>"

    def run(batches):
        for b in batches:
            at, ie = (b.column(c).flatten().to_numpy(zero_copy_only=False).reshape(-1, spec.dim) for c in ("x", "ie"))
            val, grad = _tables(spec, at, ie)
            lists = lambda flat, n: pa.ListArray.from_arrays(np.arange(0, len(flat) + 1, n, dtype=np.int32), flat)
            inner = lists(pa.array(grad.reshape(-1)), spec.dim)
            cols = [b.column("e"), b.column("q"), b.column("x"), b.column("w"), lists(pa.array(val.reshape(-1)), spec.n_ldof), lists(inner, spec.n_ldof)]
            yield pa.RecordBatch.from_arrays(cols, ["e", "q", "x", "w", "n", "g"])

    return quadrature(spark, spec, n).select("e", "q", "ie", "x", "w").mapInArrow(run, schema)


def coupling_map(points: DataFrame, g: MeshSpec) -> DataFrame:
    """Each local integration point's host element and reference coordinates there; no shuffle."""
    found = locate_bucket(points, g)
    xi = [(F.col("x")[a] - g.lo[a]) / g.h[a] * 2 - 2 * F.col("ie_g")[a] - 1 for a in range(g.dim)]
    return found.withColumn("xi_g", F.array(*xi))


def crossed_elements(coupling: DataFrame) -> DataFrame:
    """Rows (e_l, e_g, n_q): the pairs of a local element and a global element that it crosses."""
    return coupling.groupBy(F.col("e").alias("e_l"), "e_g").agg(F.count(F.lit(1)).alias("n_q"))


def crossed_by_overlap(spark: SparkSession, local: MeshSpec, g: MeshSpec, tol: float = TOLERANCE) -> DataFrame:
    """Rows (e_l, e_g): pairs of elements whose boxes overlap, by arithmetic on span ranges."""
    ie = digits("id", local.n_el)
    spans = []
    for a in range(g.dim):
        lo, hi = F.lit(local.lo[a]) + ie[a] * local.h[a], F.lit(local.lo[a]) + (ie[a] + 1) * local.h[a]
        first = F.floor((lo - g.lo[a]) / g.h[a] + tol)
        last = F.ceil((hi - g.lo[a]) / g.h[a] - tol) - 1
        spans.append(F.sequence(F.greatest(F.lit(0), first).cast("int"), F.least(F.lit(g.n_el[a] - 1), last).cast("int")))
    out = spark.range(local.n_elements).select(F.col("id").alias("e_l"), *[s.alias(f"s{a}") for a, s in enumerate(spans)])
    for a in range(g.dim):
        out = out.withColumn(f"s{a}", F.explode(f"s{a}"))
    return out.select("e_l", encode([F.col(f"s{a}") for a in range(g.dim)], g.n_el).alias("e_g"))
