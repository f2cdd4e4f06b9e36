"""Element matrices of box meshes for whole batches of elements, by full quadrature, as dense array products."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from . import basis
from .geometry import TOLERANCE, gauss_points
from .meshes import MeshSpec

#: Elements whose tables are held at one time.
BATCH = 64


def unrank(e: np.ndarray, sizes: tuple[int, ...]) -> np.ndarray:
    out = np.empty((len(e), len(sizes)), np.int64)
    for a, n in enumerate(sizes):
        out[:, a] = e % n
        e = e // n
    return out


def _outer(parts: list[np.ndarray]) -> np.ndarray:
    """Tables (elements, points, functions) of the axes to those of the box, the first axis fastest."""
    out = parts[0]
    for f in parts[1:]:
        out = (f[:, :, None, :, None] * out[:, None, :, None, :]).reshape(len(out), f.shape[1] * out.shape[1], f.shape[2] * out.shape[2])
    return out


@dataclass
class AxisTables:
    """Of each axis and span: values and slopes at the rule's points; and the points and their weights."""

    val: list[np.ndarray]
    der: list[np.ndarray]
    x: list[np.ndarray]
    w: list[np.ndarray]


def axis_tables(spec: MeshSpec, n: int, at: AxisTables | None = None) -> AxisTables:
    """Tables of a mesh at its own points, or at those of another mesh (rows are then that mesh's spans, hosts by search)."""
    r, rw = (np.array(t) for t in gauss_points(n))
    val, der, xs, ws = [], [], [], []
    for a in range(spec.dim):
        h = spec.h[a]
        if at is None:
            span = np.repeat(np.arange(spec.n_el[a]), n)
            x = spec.lo[a] + (span + np.tile((r + 1) / 2, spec.n_el[a])) * h
            ws.append(rw * h / 2)
        else:
            x = at.x[a].reshape(-1)
            span = np.clip(np.floor((x - spec.lo[a]) / h + TOLERANCE).astype(np.int64), 0, spec.n_el[a] - 1)
            ws.append(span.reshape(-1, n))  # here: the host span of each point
        v, d = basis.axis_values(spec, a, x, span)
        val.append(v.reshape(-1, n, v.shape[1]))
        der.append(d.reshape(-1, n, d.shape[1]))
        xs.append(x.reshape(-1, n))
    return AxisTables(val, der, xs, ws)


def _slopes(t: AxisTables, ie: np.ndarray) -> np.ndarray:
    """(elements, dim * points, functions): the gradients' components one after the other."""
    dim = ie.shape[1]
    return np.concatenate([_outer([(t.der if a == d else t.val)[a][ie[:, a]] for a in range(dim)]) for d in range(dim)], axis=1)


def _product(left: AxisTables, right: AxisTables, il: np.ndarray, ir: np.ndarray, w: np.ndarray, form: str) -> np.ndarray:
    """(elements, functions, functions): sums over points of the form's integrand; forms add up, as "laplace+mass"."""
    out, dim = 0.0, il.shape[1]
    if "laplace" in form:
        out = np.matmul((_slopes(left, il) * np.tile(w, (1, dim))[:, :, None]).transpose(0, 2, 1), _slopes(right, ir))
    if "mass" in form:
        a, b = (_outer([t.val[d][i[:, d]] for d in range(dim)]) for t, i in ((left, il), (right, ir)))
        out = out + np.matmul((a * w[:, :, None]).transpose(0, 2, 1), b)
    return out


def own_values(spec: MeshSpec, e: np.ndarray, n: int = 4, form: str = "laplace", tables: AxisTables | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(ids, values) of elements' own matrices."""
    t = tables or axis_tables(spec, n)
    w = _weights(t.w)[None]
    ids, out = [np.zeros((0, spec.n_ldof), np.int64)], [np.zeros((0, spec.n_ldof, spec.n_ldof))]
    for at in range(0, len(e), BATCH):
        ie = unrank(e[at : at + BATCH], spec.n_el)
        out.append(_product(t, t, ie, ie, w, form))
        ids.append(vertex_ids(spec, ie))
    return np.concatenate(ids), np.concatenate(out)


def _weights(w: list[np.ndarray]) -> np.ndarray:
    out = w[0]
    for f in w[1:]:
        out = (f[:, None] * out[None, :]).reshape(-1)
    return out


def vertex_ids(spec: MeshSpec, ie: np.ndarray) -> np.ndarray:
    pos = unrank(np.arange(spec.n_ldof), (spec.degree + 1,) * spec.dim)
    return ((ie[:, None, :] * spec.step + pos[None]) * np.cumprod([1, *spec.n_cp[:-1]])).sum(-1) + spec.offset


class OwnBlock:
    """The Laplace block of one mesh, for rows that one part owns, on the stencil of index offsets."""

    def __init__(self, spec: MeshSpec, rows: np.ndarray, n: int = 4):
        self.spec, self.rows, self.tables = spec, rows, axis_tables(spec, n)
        self.w = np.sqrt(np.tile(_weights(self.tables.w), spec.dim))
        self.reach = 2 * spec.degree + 1
        self.sums = np.zeros((len(rows), self.reach**spec.dim))
        pos = unrank(np.arange(spec.n_ldof), (spec.degree + 1,) * spec.dim)
        gap = pos[None] - pos[:, None] + spec.degree  # from function a to function b
        self.slot = (gap * self.reach ** np.arange(spec.dim)).sum(-1)

    def add(self, e: np.ndarray) -> None:
        """Evaluate these elements and keep the rows that are owned."""
        for at in range(0, len(e), BATCH):
            ie = unrank(e[at : at + BATCH], self.spec.n_el)
            g = _slopes(self.tables, ie) * self.w[None, :, None]
            k = np.matmul(g.transpose(0, 2, 1), g)
            v = vertex_ids(self.spec, ie)
            place = np.searchsorted(self.rows, v)
            own = self.rows[np.minimum(place, len(self.rows) - 1)] == v if len(self.rows) else np.zeros(v.shape, bool)
            for a in range(self.spec.n_ldof):
                # one function of different elements is a different row each time
                hit = own[:, a]
                self.sums[place[hit, a][:, None], self.slot[a][None]] += k[hit, a]

    def entries(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(row index, column id, value) of the owned rows, columns rising."""
        ix = unrank(self.rows - self.spec.offset, self.spec.n_cp)
        gap = unrank(np.arange(self.reach**self.spec.dim), (self.reach,) * self.spec.dim) - self.spec.degree
        size, stride = np.array(self.spec.n_cp), np.cumprod([1, *self.spec.n_cp[:-1]])
        inside = np.ones(self.sums.shape, bool)
        for a in range(self.spec.dim):
            to = ix[:, a][:, None] + gap[:, a][None]
            inside &= (to >= 0) & (to < size[a])
        r, s = np.nonzero(inside)
        return r, (self.rows[r] + (gap * stride).sum(1)[s]), self.sums[r, s]


def crossed(local: MeshSpec, g: MeshSpec, e_l: np.ndarray, n: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """The cells of local elements: each with every global element that holds a point of it."""
    hosts = axis_tables(g, n, axis_tables(local, n)).w
    il = unrank(e_l, local.n_el)
    number, stride = np.zeros((len(e_l), 1), np.int64), 1
    for a in range(g.dim):
        number = (number[:, None, :] + hosts[a][il[:, a]][:, :, None] * stride).reshape(len(e_l), -1)
        stride *= g.n_el[a]
    pairs = np.unique(np.stack([np.repeat(e_l, number.shape[1]), number.reshape(-1)], 1), axis=0)
    return pairs[:, 0], pairs[:, 1]


def coupling_values(local: MeshSpec, g: MeshSpec, e_l: np.ndarray, e_g: np.ndarray, n: int = 4, form: str = "laplace") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(global ids, local ids, values) of cells: pairs of a local element and one global element that it crosses."""
    own = axis_tables(local, n)
    other = axis_tables(g, n, own)
    w = _weights(own.w)
    rows, cols, out = [], [], []
    for at in range(0, len(e_l), BATCH):
        il, ig = unrank(e_l[at : at + BATCH], local.n_el), unrank(e_g[at : at + BATCH], g.n_el)
        out.append(_product(other, own, il, il, hosted(other, il, ig) * w[None], form))
        rows.append(vertex_ids(g, ig))
        cols.append(vertex_ids(local, il))
    if not out:
        return np.zeros((0, g.n_ldof), np.int64), np.zeros((0, local.n_ldof), np.int64), np.zeros((0, g.n_ldof, local.n_ldof))
    return np.concatenate(rows), np.concatenate(cols), np.concatenate(out)


def at_points(points: AxisTables, tables: AxisTables, ie: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(coordinates, weights, function values) at the points of elements; ``tables`` may be those of the other mesh there."""
    dim = ie.shape[1]
    x = np.stack([_outer([(points.x[b] if b == a else np.ones_like(points.x[b]))[ie[:, b]][:, :, None] for b in range(dim)])[:, :, 0] for a in range(dim)], -1)
    return x, _weights(points.w)[None], _outer([tables.val[a][ie[:, a]] for a in range(dim)])


def hosted(tables: AxisTables, il: np.ndarray, ig: np.ndarray) -> np.ndarray:
    """(cells, points): 1 where the point of the local element lies in the cell's global element."""
    return _outer([(tables.w[a][il[:, a]] == ig[:, a][:, None]).astype(float)[:, :, None] for a in range(il.shape[1])])[:, :, 0]


def load_values(spec: MeshSpec, e: np.ndarray, f, n: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """(ids, integrals of f times each function) of elements."""
    t = axis_tables(spec, n)
    ids, out = [], []
    for at in range(0, len(e), BATCH):
        ie = unrank(e[at : at + BATCH], spec.n_el)
        x, w, val = at_points(t, t, ie)
        out.append(np.einsum("eq,eqi->ei", f(x) * w, val))
        ids.append(vertex_ids(spec, ie))
    return (np.concatenate(ids), np.concatenate(out)) if out else (np.zeros((0, spec.n_ldof), np.int64), np.zeros((0, spec.n_ldof)))


def fold(i: np.ndarray, j: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Entries summed by (i, j), sorted."""
    order = np.lexsort((j, i))
    i, j, v = i[order], j[order], v[order]
    new = np.ones(len(i), bool)
    new[1:] = (i[1:] != i[:-1]) | (j[1:] != j[:-1])
    at = np.flatnonzero(new)
    return i[at], j[at], np.add.reduceat(v, at) if len(at) else v
