"""Matrix and right-hand-side generation for the blocks of two overlaid meshes.

Dense work per element runs in numpy over Arrow batches; what leaves a batch is already summed over
its integration points. Sums across elements are one aggregation by (i, j).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import basis, elements
from .geometry import TOLERANCE, gauss_points
from .graph import offsets
from .meshes import MeshSpec, digits, encode

ENTRY = "i long, j long, val double"


_unrank = elements.unrank


def _vertex_ids(spec: MeshSpec, ie: np.ndarray) -> np.ndarray:
    """Ordered vertex ids of elements given by multi-index: (elements, functions)."""
    m = spec.degree + 1
    pos = _unrank(np.arange(spec.n_ldof), (m,) * spec.dim)
    ix = ie[:, None, :] * spec.step + pos[None]
    strides = np.cumprod([1, *spec.n_cp[:-1]])
    return (ix * strides).sum(-1) + spec.offset


def _values(spec: MeshSpec, x: np.ndarray, ie: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    parts = [basis.axis_values(spec, a, x[:, a], ie[:, a]) for a in range(spec.dim)]
    return basis.tensor([p[0] for p in parts], [p[1] for p in parts])


def _host(spec: MeshSpec, x: np.ndarray, tol: float = TOLERANCE) -> np.ndarray:
    i = np.floor((x - np.array(spec.lo)) / np.array(spec.h) + tol).astype(np.int64)
    return np.clip(i, 0, np.array(spec.n_el) - 1)


#: A function of element numbers (an array, or two for cells) to (rows, columns, values) of their matrices.
Block = Callable[..., tuple[np.ndarray, np.ndarray, np.ndarray]]


def _flat(i: np.ndarray, j: np.ndarray, val: np.ndarray) -> tuple:
    return np.repeat(i, j.shape[1], axis=1).reshape(-1), np.tile(j, (1, i.shape[1])).reshape(-1), val.reshape(-1)


def own_block(spec: MeshSpec, n: int, form: str) -> Block:
    """Elements' own matrices; a batch is one array product."""
    tables = elements.axis_tables(spec, n)

    def make(e: np.ndarray) -> tuple:
        ids, val = elements.own_values(spec, e, n, form, tables)
        return _flat(ids, ids, val)

    return make


def coupling_block(local: MeshSpec, g: MeshSpec, n: int, form: str) -> Block:
    """Local elements' (or cells') coupling with the global functions."""

    def make(e_l: np.ndarray, e_g: np.ndarray | None = None) -> tuple:
        if e_g is None:
            e_l, e_g = elements.crossed(local, g, e_l, n)
        return _flat(*elements.coupling_values(local, g, e_l, e_g, n, form))

    return make


def _emit(i: np.ndarray, j: np.ndarray, val: np.ndarray, **extra: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({**{k: pa.array(x) for k, x in extra.items()}, "i": pa.array(i), "j": pa.array(j), "val": pa.array(val)})


#: Elements that are evaluated before their entries are summed.
CHUNK = 256


def block_entries(elements_: DataFrame, make: Block, chunk: int = CHUNK) -> DataFrame:
    """Partial entries of rows (e) or (e_l, e_g), summed within each chunk of elements."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in b.columns]
            for at in range(0, b.num_rows, chunk):
                yield _emit(*elements.fold(*make(*[c[at : at + chunk] for c in cols])))

    return elements_.mapInArrow(run, ENTRY)


def assemble(entries: DataFrame) -> DataFrame:
    return entries.groupBy("i", "j").agg(F.sum("val").alias("val"))


def k_own(spark: SparkSession, spec: MeshSpec, n: int = 4, form: str = "laplace") -> DataFrame:
    """A mesh's own block by quadrature over all its elements."""
    return assemble(block_entries(spark.range(spec.n_elements).withColumnRenamed("id", "e"), own_block(spec, n, form)))


def k_coupling(spark: SparkSession, local: MeshSpec, g: MeshSpec, n: int = 4, form: str = "laplace") -> DataFrame:
    """The block between global rows and local columns; the hosts come from arithmetic, not from a search."""
    return assemble(block_entries(spark.range(local.n_elements).withColumnRenamed("id", "e"), coupling_block(local, g, n, form)))


def transpose(k: DataFrame) -> DataFrame:
    return k.select(F.col("j").alias("i"), F.col("i").alias("j"), "val")


def block_system(gg: DataFrame, gl: DataFrame, ll: DataFrame) -> DataFrame:
    """All four blocks with their names; the form is symmetric, so the fourth is the transpose of the second."""
    named = [(gg, "GG"), (gl, "GL"), (transpose(gl), "LG"), (ll, "LL")]
    return reduce(DataFrame.unionByName, [d.withColumn("blk", F.lit(n)) for d, n in named])


def axis_matrices(spec: MeshSpec, axis: int, n: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """(mass, stiffness) of one axis as dense arrays of the axis' own size."""
    x, w = (np.array(r) for r in gauss_points(n))
    size, h = spec.n_cp[axis], spec.h[axis]
    mass, stiff = np.zeros((size, size)), np.zeros((size, size))
    for s in range(spec.n_el[axis]):
        val, der = basis.axis_values(spec, axis, spec.lo[axis] + (s + (x + 1) / 2) * h, np.full(n, s))
        at = s * spec.step + np.arange(spec.degree + 1)
        mass[np.ix_(at, at)] += np.einsum("q,qi,qj->ij", w * h / 2, val, val)
        stiff[np.ix_(at, at)] += np.einsum("q,qi,qj->ij", w * h / 2, der, der)
    return mass, stiff


def k_structured(spark: SparkSession, spec: MeshSpec, n: int = 4) -> DataFrame:
    """The Laplace block of a box mesh from one-dimensional matrices: vertices times offsets, no shuffle.

    The broadcast tables have one row per neighbour pair of one axis: they grow with the length
    of an axis, not with the mesh.
    """
    p, dim = spec.degree, spec.dim
    out = spark.range(spec.n_vertices).withColumnRenamed("id", "a").crossJoin(F.broadcast(offsets(spark, p, dim)))
    ix = digits("a", spec.n_cp)
    for k in range(dim):
        m, s = axis_matrices(spec, k, n)
        rows = [(i, i + d, float(m[i, i + d]), float(s[i, i + d])) for i in range(spec.n_cp[k]) for d in range(-p, p + 1) if 0 <= i + d < spec.n_cp[k]]
        table = spark.createDataFrame(rows, f"i{k} int, j{k} int, m{k} double, s{k} double")
        out = out.withColumn(f"i{k}", ix[k]).withColumn(f"j{k}", F.col(f"i{k}") + F.col("d")[k]).join(F.broadcast(table), [f"i{k}", f"j{k}"])

    def term(d: int) -> Column:
        return reduce(lambda x, y: x * y, [F.col(f"{'s' if a == d else 'm'}{a}") for a in range(dim)])

    return out.select((F.col("a") + spec.offset).alias("i"), (encode([F.col(f"j{k}") for k in range(dim)], spec.n_cp) + spec.offset).alias("j"), reduce(lambda x, y: x + y, [term(d) for d in range(dim)]).alias("val"))


def assemble_owned(assigned: DataFrame, make: Block, part: DataFrame, n_dom: int) -> DataFrame:
    """Rows (k, i, j, val): every part computes its assigned elements and keeps the rows it owns.

    Element numbers and core vertices go to their part, entries go nowhere: a part's elements meet its core in one
    task, which sums its rows and returns them. Elements that several parts need are computed by each. A
    part's rows must fit a task; ``n_dom`` is chosen for that.
    """
    names = [c for c in assigned.columns if c not in ("k", "n_core")]

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        core = np.sort(right["v"].to_numpy())
        k = right["at"][0].as_py() if len(right) else 0
        cols = [left[c].to_numpy() for c in names]
        held: list[tuple] = []
        size = 0
        for at in range(0, len(left) if len(core) else 0, CHUNK):
            i, j, val = make(*[c[at : at + CHUNK] for c in cols])
            mine = core[np.minimum(np.searchsorted(core, i), len(core) - 1)] == i
            held.append(elements.fold(i[mine], j[mine], val[mine]))
            size += len(held[-1][0])
            if size > 4 * len(held[0][0]) + (1 << 20):  # sums take the place of their terms
                held = [elements.fold(*(np.concatenate(c) for c in zip(*held, strict=True)))]
                size = len(held[0][0])
        i, j, val = elements.fold(*(np.concatenate(c) for c in zip(*held, strict=True))) if held else (np.zeros(0, np.int64),) * 2 + (np.zeros(0),)
        return pa.Table.from_batches([_emit(i, j, val, k=np.full(len(i), k, np.int32))])

    both = assigned.select("k", *names).groupBy("k").cogroup(part.select(F.col("k").alias("at"), "v").groupBy("at"))
    return both.applyInArrow(run, "k int, " + ENTRY)


def rhs(spark: SparkSession, spec: MeshSpec, f: Callable[[np.ndarray], np.ndarray], n: int = 4) -> DataFrame:
    """Rows (v, val): integrals of f times each function."""

    def make(e: np.ndarray) -> tuple:
        ids, val = elements.load_values(spec, e, f, n)
        return ids.reshape(-1), np.zeros(ids.size, np.int64), val.reshape(-1)

    return assemble(block_entries(spark.range(spec.n_elements).withColumnRenamed("id", "e"), make)).select(F.col("i").alias("v"), "val")


# ---- data rows as integration points --------------------------------------------------------


def gram_entries(points: DataFrame, a: MeshSpec, b: MeshSpec | None = None) -> DataFrame:
    """Entries sum_rows w N_i N_j from rows (x, w); with two meshes, of a's rows and b's columns.

    A batch is summed per host element before anything leaves it.
    """
    b_spec = b or a

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, a.dim)
            w = batch.column("w").to_numpy(zero_copy_only=False)
            ha, hb = _host(a, x), _host(b_spec, x)
            na, nb = _values(a, x, ha)[0], _values(b_spec, x, hb)[0]
            va, vb = _vertex_ids(a, ha), _vertex_ids(b_spec, hb)
            # rows of one pair of hosts stand together, and each group is one matrix product
            key = np.ravel_multi_index((*ha.T, *hb.T), (*a.n_el, *b_spec.n_el))
            order = np.argsort(key, kind="stable")
            first = np.flatnonzero(np.diff(key[order], prepend=-1))
            wa, nb = (na * w[:, None])[order], nb[order]
            k = np.stack([wa[s:e].T @ nb[s:e] for s, e in zip(first, np.append(first[1:], len(key)), strict=True)])
            yield _emit(*elements.fold(*_flat(va[order[first]], vb[order[first]], k)))

    return points.select("x", "w").mapInArrow(run, ENTRY)


def gram_rhs(points: DataFrame, spec: MeshSpec, target: str) -> DataFrame:
    """Rows (v, val): sum_rows w N_v times the target column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, spec.dim)
            y = batch.column("w").to_numpy(zero_copy_only=False) * batch.column("y").to_numpy(zero_copy_only=False)
            host = _host(spec, x)
            v, val = _vertex_ids(spec, host), _values(spec, x, host)[0] * y[:, None]
            yield _emit(*elements.fold(v.reshape(-1), np.zeros(v.size, np.int64), val.reshape(-1)))

    return assemble(points.select("x", "w", F.col(target).alias("y")).mapInArrow(run, ENTRY)).select(F.col("i").alias("v"), "val")


# ---- boundary values and storage -------------------------------------------------------------


def apply_dirichlet(k: DataFrame, f: DataFrame, fixed: DataFrame, mode: str = "eliminate") -> tuple[DataFrame, DataFrame]:
    """(matrix, right-hand side) with vertices (v, value) fixed.

    ``eliminate`` drops fixed rows and columns and moves known values to the right-hand side;
    ``identity`` keeps them as unit rows, with the same solution.
    """
    known_j = fixed.select(F.col("v").alias("j"), F.col("value").alias("gj"))
    known_i = fixed.select(F.col("v").alias("i"))
    marked = k.join(known_j, "j", "left").join(known_i.withColumn("fi", F.lit(True)), "i", "left")
    free = marked.where("fi is null and gj is null").select("i", "j", "val")
    lift = marked.where("fi is null and gj is not null").groupBy(F.col("i").alias("v")).agg(F.sum(F.col("val") * F.col("gj")).alias("lift"))
    right = f.join(fixed.select("v"), "v", "left_anti").join(lift, "v", "left").select("v", (F.col("val") - F.coalesce("lift", F.lit(0.0))).alias("val"))
    if mode == "eliminate":
        return free, right
    ones = fixed.select(F.col("v").alias("i"), F.col("v").alias("j"), F.lit(1.0).alias("val"))
    return free.unionByName(ones), right.unionByName(fixed.select("v", F.col("value").alias("val")))


def on_pattern(k: DataFrame, pattern: DataFrame) -> DataFrame:
    """The matrix on its candidate pattern: entries that happen to be zero are stored too."""
    return pattern.join(k, ["i", "j"], "left").select("i", "j", F.coalesce("val", F.lit(0.0)).alias("val"))


def to_rows(k: DataFrame) -> DataFrame:
    """Row-grouped form (i, nbr); a row has at most the neighbours of one vertex."""
    return k.groupBy("i").agg(F.array_sort(F.collect_list(F.struct("j", "val"))).alias("nbr"))


def to_entries(rows: DataFrame) -> DataFrame:
    return rows.select("i", F.inline("nbr"))
