"""Structured meshes, incidence meshes and the numbering that all of them share."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from math import prod

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The ids of mesh number m start at m * MESH_STRIDE; the global mesh is number 0.
MESH_STRIDE = 1 << 40


@dataclass(frozen=True)
class MeshSpec:
    """A box mesh: open uniform splines, or Lagrange elements of any order, per axis alike."""

    mesh: str
    family: str  # "spline" or "lagrange"
    degree: int
    n_el: tuple[int, ...]
    lo: tuple[float, ...]
    hi: tuple[float, ...]
    number: int = 0

    @property
    def dim(self) -> int:
        return len(self.n_el)

    @property
    def n_cp(self) -> tuple[int, ...]:
        return tuple(n + self.degree if self.family == "spline" else n * self.degree + 1 for n in self.n_el)

    @property
    def h(self) -> tuple[float, ...]:
        return tuple((b - a) / n for a, b, n in zip(self.lo, self.hi, self.n_el, strict=True))

    @property
    def offset(self) -> int:
        return self.number * MESH_STRIDE

    @property
    def n_vertices(self) -> int:
        return prod(self.n_cp)

    @property
    def n_elements(self) -> int:
        return prod(self.n_el)

    @property
    def n_ldof(self) -> int:
        return (self.degree + 1) ** self.dim

    @property
    def step(self) -> int:
        """Vertices per axis from one element to the next."""
        return 1 if self.family == "spline" else self.degree


def box_pair(n_global: int, degree: int, n_local: int, side: float, dim: int = 3) -> tuple[MeshSpec, MeshSpec]:
    """A spline mesh on the unit box and a linear mesh on the corner box of the given side."""
    g = MeshSpec("G", "spline", degree, (n_global,) * dim, (0.0,) * dim, (1.0,) * dim, 0)
    return g, MeshSpec("L", "lagrange", 1, (n_local,) * dim, (0.0,) * dim, (side,) * dim, 1)


def validate_overlay(g: MeshSpec, local: MeshSpec, tol: float = 1e-8) -> None:
    """The local box must lie in the global one; their boundaries may touch."""
    if g.dim != local.dim or any(a < b - tol for a, b in zip(local.lo, g.lo, strict=True)) or any(a > b + tol for a, b in zip(local.hi, g.hi, strict=True)):
        raise ValueError("the local mesh must lie inside the global mesh")


def digits(col: Column | str, sizes: tuple[int, ...]) -> list[Column]:
    """The digits of an id in mixed radix, the first axis running fastest."""
    c = F.col(col) if isinstance(col, str) else col
    out = []
    for n in sizes:
        out.append((c % n).cast("int"))
        c = ((c - c % n) / n).cast("long")
    return out


def encode(ix: list[Column], sizes: tuple[int, ...]) -> Column:
    total, stride = F.lit(0).cast("long"), 1
    for c, n in zip(ix, sizes, strict=True):
        total = total + c.cast("long") * stride
        stride *= n
    return total


def encode_vertex(spec: MeshSpec, ix: list[Column]) -> Column:
    return encode(ix, spec.n_cp) + spec.offset


def decode_vertex(spec: MeshSpec, v: Column) -> list[Column]:
    return digits(v - spec.offset, spec.n_cp)


def open_knots(lo: float, hi: float, n_el: int, degree: int) -> list[float]:
    """Open knot vector with simple interior knots: n_el + 2 * degree + 1 values."""
    inner = [lo + (hi - lo) * i / n_el for i in range(n_el + 1)]
    return [lo] * degree + inner + [hi] * degree


def knot_at(spec: MeshSpec, axis: int, i: Column) -> Column:
    """Knot number i of an axis, by arithmetic instead of a table."""
    n, p = spec.n_el[axis], spec.degree
    span = F.greatest(F.lit(0), F.least(F.lit(n), i - p))
    return F.lit(spec.lo[axis]) + span * (spec.hi[axis] - spec.lo[axis]) / n


def knot_vector(spark: SparkSession, spec: MeshSpec, axis: int = 0) -> DataFrame:
    n = spec.n_el[axis] + 2 * spec.degree + 1
    return spark.range(n).select(F.col("id").cast("int").alias("i"), knot_at(spec, axis, F.col("id")).alias("knot"))


def point_of(spec: MeshSpec, axis: int, i: Column) -> Column:
    """Coordinate of a vertex along an axis: the mean of its inner knots, or the node itself."""
    a, b, n, p = spec.lo[axis], spec.hi[axis], spec.n_el[axis], spec.degree
    if spec.family == "lagrange":
        return F.lit(a) + i * (b - a) / (n * p)
    inner = reduce(lambda x, y: x + y, [F.greatest(F.lit(0), F.least(F.lit(n), i + m - p)) for m in range(1, p + 1)])
    return F.lit(a) + inner * (b - a) / (n * p)


def greville(knots: DataFrame, degree: int) -> DataFrame:
    """Rows (i, x): the points of the functions on an axis given by its distinct span faces (t), the ends repeated to an open knot vector.

    One row a face, so one axis is ordered in one task.
    """
    at = Window.orderBy("t", "copy")
    ends = knots.agg(F.min("t").alias("lo"), F.max("t").alias("hi"))
    copies = F.when(F.col("t").isin(F.col("lo"), F.col("hi")), degree).otherwise(1)
    inner = knots.crossJoin(F.broadcast(ends)).select("t", F.explode(F.sequence(F.lit(1), copies)).alias("copy"))
    run = [F.lead("t", m).over(at) if m else F.col("t") for m in range(degree)]
    rows = inner.select((F.row_number().over(at) - 1).cast("long").alias("i"), (reduce(lambda a, b: a + b, run) / degree).alias("x"))
    return rows.where("x is not null")


def vertices(spark: SparkSession, spec: MeshSpec, parts: int | None = None) -> DataFrame:
    """Rows (v, mesh, ix, x, fixed): ``fixed`` marks vertices on the box's boundary."""
    ids = spark.range(0, spec.n_vertices, 1, parts) if parts else spark.range(spec.n_vertices)
    ix = digits("id", spec.n_cp)
    edge = reduce(lambda a, b: a | b, [(c == 0) | (c == n - 1) for c, n in zip(ix, spec.n_cp, strict=True)])
    return ids.select(
        (F.col("id") + spec.offset).alias("v"), F.lit(spec.mesh).alias("mesh"), F.array(*ix).alias("ix"),
        F.array(*[point_of(spec, a, c) for a, c in enumerate(ix)]).alias("x"), edge.alias("fixed"),
    )


def mark_dirichlet(vertex: DataFrame, value: Column | None = None) -> DataFrame:
    """Fixed vertices get a value (0 unless given); free ones get null."""
    return vertex.withColumn("value", F.when(F.col("fixed"), F.lit(0.0) if value is None else value))


def elements(spark: SparkSession, spec: MeshSpec) -> DataFrame:
    """Rows (mesh, e, ie, vs): the multi-index and the ordered vertex list of each element."""
    ie = digits("id", spec.n_el)
    m = spec.degree + 1

    def vertex(pos: Column) -> Column:
        own = [ie[a] * spec.step + F.floor(pos / m**a).cast("int") % m for a in range(spec.dim)]
        return encode_vertex(spec, own)

    return spark.range(spec.n_elements).select(
        F.lit(spec.mesh).alias("mesh"), F.col("id").alias("e"), F.array(*ie).alias("ie"), F.transform(F.sequence(F.lit(0), F.lit(spec.n_ldof - 1)), vertex).alias("vs")
    )


def incidence(spark: SparkSession, spec: MeshSpec) -> DataFrame:
    """Rows (mesh, e, pos, v), the long form of the element lists."""
    return elements(spark, spec).select("mesh", "e", F.posexplode("vs").alias("pos", "v"))


def structured_mesh(spark: SparkSession, spec: MeshSpec) -> tuple[DataFrame, DataFrame]:
    return vertices(spark, spec), elements(spark, spec)


def incidence_mesh(df: DataFrame, element: Column, vertex: Column, mesh: str) -> DataFrame:
    """A mesh from data: distinct pairs of an element key and a vertex id; nulls take no part."""
    return df.select(F.lit(mesh).alias("mesh"), element.alias("e"), vertex.alias("v")).where("e is not null and v is not null").distinct()


def overlay(specs: list[MeshSpec], spark: SparkSession) -> DataFrame:
    """The vertices of a global mesh and any number of local ones, in one id space."""
    for s in specs[1:]:
        validate_overlay(specs[0], s)
    return reduce(DataFrame.unionByName, [vertices(spark, s) for s in specs])


def supports(spark: SparkSession, spec: MeshSpec) -> DataFrame:
    """Rows (v, mesh, lo, hi): the box on which a basis function is not zero."""
    ix = digits("id", spec.n_cp)
    n, p = spec.n_el, spec.degree
    if spec.family == "spline":
        first = [F.greatest(F.lit(0), c - p) for c in ix]
        last = [F.least(F.lit(n[a]), c + 1) for a, c in enumerate(ix)]
    else:
        # an element border belongs to both of its elements, an inner node to one
        first = [F.greatest(F.lit(0), F.ceil(c / p) - 1) for c in ix]
        last = [F.least(F.lit(n[a]), F.floor(c / p) + 1) for a, c in enumerate(ix)]
    place = lambda a, c: F.lit(spec.lo[a]) + c * (spec.hi[a] - spec.lo[a]) / n[a]
    return spark.range(spec.n_vertices).select(
        (F.col("id") + spec.offset).alias("v"), F.lit(spec.mesh).alias("mesh"),
        F.array(*[place(a, c) for a, c in enumerate(first)]).alias("lo"), F.array(*[place(a, c) for a, c in enumerate(last)]).alias("hi"),
    )
