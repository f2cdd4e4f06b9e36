"""Partition-local generation and solution: one barrier stage in which every part's matrix stays in its task.

A part is placed by its number (``repartitionById``). Its task evaluates the elements and cells that touch its core,
keeps the rows it owns, and then iterates with the others: before each product it receives the halo values from
their owners, over direct connections, and nothing else moves but the few scalars of the dot products, which cover
core values only. What a task holds is its parts' rows, so parts are sized to a task's memory. A barrier stage is
repeated as a whole, from its stored input, when a task or an executor is lost.
"""

from __future__ import annotations

import secrets
import socket
import struct
import threading
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import BarrierTaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import store
from . import elements, subdomain
from .meshes import MeshSpec, incidence, vertices

#: Kinds of rows that go into a task (fixed values): elements of both meshes, cells, core and halo vertices.
EL_G, EL_L, CELL, CORE, HALO = range(5)
#: Kinds of rows that come out: solution, seconds by part and component, sums by block, the run's end, squared errors.
SOLUTION, SECONDS, BLOCK, END, ERROR = range(5)
COMPONENTS = ("gg", "ll", "gl", "rhs", "rows", "connect", "solve")
BLOCKS = ("GG", "LL", "GL", "LG")
OUT = "kind int, k int, a long, name string, val double"


@dataclass
class Run:
    """What a barrier run left behind, as one stored table."""

    rows: DataFrame

    @property
    def x(self) -> DataFrame:
        return self.rows.where(F.col("kind") == SOLUTION).select(F.col("a").alias("v"), F.col("val").alias("x"))

    @property
    def seconds(self) -> DataFrame:
        """Rows (k, name, val): measured seconds of each part and component."""
        return self.rows.where(F.col("kind") == SECONDS).select("k", "name", "val")

    def costs(self) -> DataFrame:
        """Rows (k, gg, ll, gl): measured generation, for the measures of waits, breakdowns and speedups."""
        return self.seconds.groupBy("k").pivot("name", ["gg", "ll", "gl"]).sum("val")

    @property
    def blocks(self) -> DataFrame:
        """Rows (k, name, nnz, form): stored entries of a block and its bilinear form with a fixed vector."""
        return self.rows.where(F.col("kind") == BLOCK).select("k", "name", F.col("a").alias("nnz"), F.col("val").alias("form"))

    def error(self) -> DataFrame:
        """One row: the error measure (``metrics.l2_error``) over global points outside the local box and local points inside it."""
        one = [F.sum(F.when(F.col("name") == c, F.col("val"))).alias(c) for c in ("eps_g", "eps_l", "eps_a")]
        return self.rows.where(F.col("kind") == ERROR).agg(*one).withColumn("error", F.sqrt((F.col("eps_g") + F.col("eps_l")) / F.col("eps_a")))

    def end(self) -> tuple[int, float]:
        r = self.rows.where(F.col("kind") == END).first()
        return r["a"], r["val"]


def work(spark: SparkSession, g: MeshSpec, local: MeshSpec, cells: DataFrame, part: DataFrame) -> DataFrame:
    """Rows (run, k, kind, a, b): what each part evaluates, owns and receives, from the partition and adjacency alone.

    An element or cell belongs to every part with a core vertex in it; all other vertices of these are the halo. A
    column ``run`` of the partition (0 if there is none) keeps several partitions apart.
    """
    part = part if "run" in part.columns else part.withColumn("run", F.lit(0))
    inc_g, inc_l = incidence(spark, g).select("e", "v"), incidence(spark, local).select("e", "v")
    one = F.lit(0).cast("long").alias("b")
    assigned = [store(inc.join(part, "v").select("run", "e", "k").distinct(), "work") for inc in (inc_g, inc_l)]
    ci = store(subdomain.cell_incidence(cells, inc_l, inc_g), "work")
    of_cells = store(ci.join(part, "v").select("run", "e", "k").distinct(), "work")
    met = of_cells.join(ci, "e").select("run", "k", "v")
    for a, inc in zip(assigned, (inc_g, inc_l), strict=True):
        met = met.unionByName(a.join(inc, "e").select("run", "k", "v"))
    fixed = vertices(spark, g).select("v", "fixed").unionByName(vertices(spark, local).select("v", "fixed"))
    owner = store(part.select("run", "v", F.col("k").alias("owner")).join(fixed, "v"), "work")
    near = met.distinct().join(owner, ["run", "v"])
    rows = [a.select("run", "k", F.lit(kind).alias("kind"), F.col("e").alias("a"), one) for a, kind in zip(assigned, (EL_G, EL_L), strict=True)]
    rows.append(of_cells.select("run", "k", F.lit(CELL).alias("kind"), F.col("e.e_l").alias("a"), F.col("e.e_g").alias("b")))
    rows.append(owner.select("run", F.col("owner").alias("k"), F.lit(CORE).alias("kind"), F.col("v").alias("a"), F.col("fixed").cast("long").alias("b")))
    rows.append(near.where("owner <> k").select("run", "k", F.lit(HALO).alias("kind"), F.col("v").alias("a"), (F.col("owner") * 2 + F.col("fixed").cast("int")).cast("long").alias("b")))
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return store(out, "work")


class Peers:
    """Direct connections of a barrier task: to the owners of its halo, and to the first task for sums."""

    def __init__(self, ctx: BarrierTaskContext, near: list[int], want: dict[int, np.ndarray]):
        self.rank, infos = ctx.partitionId(), ctx.getTaskInfos()
        self.size = len(infos)
        server = socket.socket()
        server.bind(("", 0))
        server.listen(self.size + len(near) + 8)
        told = [t.split("|") for t in ctx.allGather(f"{infos[self.rank].address.split(':')[0]}|{server.getsockname()[1]}|{secrets.token_hex(8)}")]
        key = "".join(t[2] for t in told).encode()[:64].ljust(64)
        self.links: dict[int, socket.socket] = {}
        self.star: dict[int, socket.socket] = {}

        def call(other: int, kind: int) -> socket.socket:
            s = socket.create_connection((told[other][0], int(told[other][1])), timeout=120)
            s.sendall(key + struct.pack("<ii", kind, self.rank))
            return s

        expected = sum(s > self.rank for s in near) + (self.size - 1 if self.rank == 0 else 0)
        for s in near:
            if s < self.rank:
                self.links[s] = call(s, 0)
        if self.rank:
            self.star[0] = call(0, 1)
        server.settimeout(120)
        while expected:
            s, _ = server.accept()
            s.settimeout(120)
            if self._read(s, 64) != key:
                s.close()
                continue
            kind, other = struct.unpack("<ii", self._read(s, 8))
            (self.links if kind == 0 else self.star)[other] = s
            expected -= 1
        server.close()
        for s in [*self.links.values(), *self.star.values()]:
            s.setsockopt(socket.IPPROTO_TCP, socket.TCP_NODELAY, 1)
            s.settimeout(600)
        # each side names the vertices that it wants
        asked = self.swap({s: np.append(len(want.get(s, ())), want.get(s, np.zeros(0))).astype(np.int64) for s in self.links}, None)
        self.asked = asked

    @staticmethod
    def _read(s: socket.socket, n: int) -> bytes:
        out = bytearray(n)
        view, at = memoryview(out), 0
        while at < n:
            got = s.recv_into(view[at:])
            if not got:
                raise ConnectionError("a peer has gone")
            at += got
        return bytes(out)

    def swap(self, out: dict[int, np.ndarray], sizes: dict[int, int] | None) -> dict[int, np.ndarray]:
        """Send an array to each neighbour and receive one; with ``sizes`` None the first number tells the length."""

        def send() -> None:
            for s, a in out.items():
                self.links[s].sendall(a.tobytes())

        sender = threading.Thread(target=send)
        sender.start()
        got = {}
        for s in sorted(self.links):
            if sizes is None:
                n = struct.unpack("<q", self._read(self.links[s], 8))[0]
                got[s] = np.frombuffer(self._read(self.links[s], 8 * n), np.int64)
            else:
                got[s] = np.frombuffer(self._read(self.links[s], 8 * sizes[s]), np.float64)
        sender.join()
        return got

    def total(self, *values: float) -> np.ndarray:
        """Sums over all tasks, added in the order of their numbers."""
        mine = np.array(values, np.float64)
        if self.size == 1:
            return mine
        if self.rank:
            self.star[0].sendall(mine.tobytes())
            return np.frombuffer(self._read(self.star[0], 8 * len(mine)), np.float64)
        parts = [mine] + [np.frombuffer(self._read(self.star[s], 8 * len(mine)), np.float64) for s in sorted(self.star)]
        out = np.sum(parts, axis=0)
        for s in self.star.values():
            s.sendall(out.tobytes())
        return out

    def close(self) -> None:
        for s in [*self.links.values(), *self.star.values()]:
            s.close()


def _probe(spec: MeshSpec, v: np.ndarray) -> np.ndarray:
    """A fixed vector for checks: products over the axes of (1 + index mod 7) / 7."""
    return np.prod((1 + elements.unrank(v - spec.offset, spec.n_cp) % 7) / 7.0, axis=1)


def _generate(g: MeshSpec, local: MeshSpec, rows: dict, n: int, f) -> tuple[list[tuple], np.ndarray, dict, list]:
    """One part: (entries by block, its right-hand side, seconds, sums by block); only owned rows, by their ids."""
    core = np.sort(rows[CORE][:, 0])
    mine = {spec.mesh: core[(core >= spec.offset) & (core < spec.offset + spec.n_vertices)] for spec in (g, local)}
    seconds, blocks, sums = {}, [], []
    for name, spec, kind in (("gg", g, EL_G), ("ll", local, EL_L)):
        start = time.perf_counter()
        own = elements.OwnBlock(spec, mine[spec.mesh], n)
        own.add(np.sort(rows[kind][:, 0]))
        r, j, val = own.entries()
        blocks.append((own.rows[r], j, val))
        seconds[name] = time.perf_counter() - start
    start = time.perf_counter()
    vg, vl, val = elements.coupling_values(local, g, rows[CELL][:, 0], rows[CELL][:, 1], n)
    i, j = np.repeat(vg, vl.shape[1], axis=1).reshape(-1), np.tile(vl, (1, vg.shape[1])).reshape(-1)
    flat = val.reshape(-1)
    for a, b, spec in ((i, j, g), (j, i, local)):
        keep = np.isin(a, mine[spec.mesh])
        blocks.append(elements.fold(a[keep], b[keep], flat[keep]))
    seconds["gl"] = time.perf_counter() - start
    start = time.perf_counter()
    right = np.zeros(len(core))
    if f is not None:
        for spec, kind in ((g, EL_G), (local, EL_L)):
            ids, part = elements.load_values(spec, np.sort(rows[kind][:, 0]), f, n)
            at = np.searchsorted(core, ids.reshape(-1))
            hit = core[np.minimum(at, max(len(core) - 1, 0))] == ids.reshape(-1) if len(core) else np.zeros(ids.size, bool)
            right += np.bincount(at[hit], weights=part.reshape(-1)[hit], minlength=len(core))
    seconds["rhs"] = time.perf_counter() - start
    for name, (i, j, val), (a, b) in zip(BLOCKS, blocks, ((g, g), (local, local), (g, local), (local, g)), strict=True):
        sums.append((name, len(val), float((val * _probe(a, i) * _probe(b, j)).sum()) if len(val) else 0.0))
    return blocks, right, seconds, sums


def _errors(g: MeshSpec, local: MeshSpec, rows: dict, n: int, exact, value_of) -> list[tuple[str, float]]:
    """One part's share of the squared errors; an element counts where its first vertex is owned."""
    core, sums = np.sort(rows[CORE][:, 0]), {"eps_g": 0.0, "eps_l": 0.0, "eps_a": 0.0}
    own = {spec.mesh: elements.axis_tables(spec, n) for spec in (g, local)}
    other = elements.axis_tables(g, n, own[local.mesh])
    hi = np.array(local.hi)

    def mine(e: np.ndarray, spec: MeshSpec) -> np.ndarray:
        return np.isin(elements.vertex_ids(spec, elements.unrank(e, spec.n_el))[:, 0], core)

    e = np.sort(rows[EL_G][:, 0])
    e = e[mine(e, g)]
    for at in range(0, len(e), elements.BATCH):
        ie = elements.unrank(e[at : at + elements.BATCH], g.n_el)
        x, w, val = elements.at_points(own[g.mesh], own[g.mesh], ie)
        want, out = exact(x), ~(x < hi).all(-1)
        u = np.einsum("eqi,ei->eq", val, value_of(elements.vertex_ids(g, ie)))
        sums["eps_g"] += float((w * out * (u - want) ** 2).sum())
        sums["eps_a"] += float((w * out * want**2).sum())
    cells = rows[CELL][mine(rows[CELL][:, 0], local)]
    for at in range(0, len(cells), elements.BATCH):
        il, ig = elements.unrank(cells[at : at + elements.BATCH, 0], local.n_el), elements.unrank(cells[at : at + elements.BATCH, 1], g.n_el)
        x, w, val = elements.at_points(own[local.mesh], own[local.mesh], il)
        here = elements.hosted(other, il, ig)
        u = np.einsum("eqi,ei->eq", val, value_of(elements.vertex_ids(local, il)))
        u = u + np.einsum("eqi,ei->eq", elements.at_points(own[local.mesh], other, il)[2], value_of(elements.vertex_ids(g, ig)))
        want = exact(x)
        sums["eps_l"] += float((w * here * (u - want) ** 2).sum())
        sums["eps_a"] += float((w * here * want**2).sum())
    return list(sums.items())


def _task(g: MeshSpec, local: MeshSpec, n: int, f, exact, solve: bool, tol: float, max_iter: int | None, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    ctx = BarrierTaskContext.get()
    got = [b for b in batches if b.num_rows]
    k, kind = (np.concatenate([b.column(c).to_numpy() for b in got]) if got else np.zeros(0, np.int64) for c in ("k", "kind"))
    ab = np.stack([np.concatenate([b.column(c).to_numpy() for b in got]) if got else np.zeros(0, np.int64) for c in ("a", "b")], 1)
    size = len(ctx.getTaskInfos())
    out: list[tuple] = []
    parts, times = [], []
    for p in np.unique(k):
        rows = {z: ab[(k == p) & (kind == z)] for z in (EL_G, EL_L, CELL, CORE, HALO)}
        blocks, right, seconds, sums = _generate(g, local, rows, n, f)
        times.append((int(p), seconds))
        out += [(SECONDS, int(p), 0, name, s) for name, s in seconds.items()] + [(BLOCK, int(p), c, name, s) for name, c, s in sums]
        parts.append((rows, blocks, right))
    if solve:
        x, ids, it, rel, spent, value_of = _iterate(ctx, size, parts, tol, max_iter)
        if exact is not None:
            for (p, _), (rows, _, _) in zip(times, parts, strict=True):
                out += [(ERROR, p, 0, name, val) for name, val in _errors(g, local, rows, n, exact, value_of)]
        out += [(SECONDS, p, 0, name, s) for p, _ in times for name, s in spent.items()]
        if ctx.partitionId() == 0:
            out.append((END, 0, it, "iterations, residual", rel))
    cols = list(zip(*out, strict=True)) if out else [[]] * 5
    types = (pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.float64())
    names = ["kind", "k", "a", "name", "val"]
    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)
    if solve and len(ids):
        m = len(ids)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(m, SOLUTION, np.int32)), pa.array(np.zeros(m, np.int32)), pa.array(ids), pa.nulls(m, pa.string()), pa.array(x)], names)


def _iterate(ctx: BarrierTaskContext, size: int, parts: list, tol: float, max_iter: int | None) -> tuple:
    """Stabilised bi-conjugate gradients on the row-scaled system of all tasks, fixed vertices left out (their values are zero)."""
    rank, begin = ctx.partitionId(), time.perf_counter()
    cores = np.concatenate([r[CORE] for r, _, _ in parts]) if parts else np.zeros((0, 2), np.int64)
    ids = np.sort(cores[cores[:, 1] == 0, 0])
    halo = np.unique(np.concatenate([r[HALO] for r, _, _ in parts]), axis=0) if parts else np.zeros((0, 2), np.int64)
    owner = (halo[:, 1] // 2) % size
    # parts of one task see each other's values directly
    near = sorted(set(owner.tolist()) - {rank})
    far = (owner != rank) & (halo[:, 1] % 2 == 0)
    want = {s: halo[far & (owner == s), 0] for s in near}
    remote = np.concatenate([want[s] for s in near]) if near else np.zeros(0, np.int64)
    order = np.argsort(np.concatenate([ids, remote]), kind="stable")
    known = np.concatenate([ids, remote])[order]
    i, j, v, b = [], [], [], np.zeros(len(ids))
    for rows, blocks, right in parts:
        core = np.sort(rows[CORE][:, 0])
        at = np.searchsorted(ids, core)
        free = np.flatnonzero(ids[np.minimum(at, max(len(ids) - 1, 0))] == core) if len(ids) else np.zeros(0, np.int64)
        b[at[free]] = right[free]
        for r, c, val in blocks:
            p, q = np.searchsorted(ids, r), np.searchsorted(known, c)
            keep = (ids[np.minimum(p, max(len(ids) - 1, 0))] == r) & (known[np.minimum(q, max(len(known) - 1, 0))] == c) if len(ids) else np.zeros(len(r), bool)
            i.append(p[keep].astype(np.int32))
            j.append(order[q[keep]].astype(np.int32))
            v.append(val[keep])
        blocks.clear()
    i, j, v = (np.concatenate(t) if t else np.zeros(0) for t in (i, j, v))
    by = np.argsort(i, kind="stable")
    i, j, v = i[by], j[by].astype(np.int64), v[by]
    first = np.searchsorted(i, np.arange(len(ids)))
    diag = np.ones(len(ids))
    on = i == j
    diag[i[on]] = v[on]
    scale = 1.0 / diag
    v *= scale[i]
    b *= scale
    spent = {"rows": time.perf_counter() - begin}
    ctx.barrier()
    begin = time.perf_counter()
    peers = Peers(ctx, near, want)
    spent["connect"] = time.perf_counter() - begin
    begin = time.perf_counter()
    give = {s: np.searchsorted(ids, a) for s, a in peers.asked.items()}
    sizes = {s: len(want[s]) for s in near}
    full, terms = np.zeros(len(known)), np.empty(len(v))

    def apply(x: np.ndarray) -> np.ndarray:
        """K_II x_I + K_IG x_G: own values, then the received ones."""
        full[: len(ids)] = x
        got = peers.swap({s: x[a] for s, a in give.items()}, sizes)
        at = len(ids)
        for s in near:
            full[at : at + sizes[s]] = got[s]
            at += sizes[s]
        if not len(ids):
            return np.zeros(0)
        np.multiply(np.take(full, j, out=terms, mode="clip"), v, out=terms)
        return np.add.reduceat(terms, first)

    x, r, p, q = np.zeros(len(ids)), b.copy(), np.zeros(len(ids)), np.zeros(len(ids))
    shadow = r.copy()
    goal, count = peers.total(r @ r, len(ids))
    limit = max_iter or int(count)
    rho, alpha, omega, new, now, it = 1.0, 1.0, 1.0, goal, goal, 0
    while goal > 0 and it < limit and now > tol * tol * goal:
        it += 1
        p = r + (new / rho) * (alpha / omega) * (p - omega * q)
        rho = new
        q = apply(p)
        alpha = rho / peers.total(shadow @ q)[0]
        s = r - alpha * q
        t = apply(s)
        ts, tt = peers.total(t @ s, t @ t)
        omega = ts / tt if tt else 0.0
        x = x + alpha * p + omega * s
        r = s - omega * t
        new, now = peers.total(shadow @ r, r @ r)
    spent["solve"] = time.perf_counter() - begin
    apply(x)  # brings the last halo values
    peers.close()
    held = full[order]

    def value_of(v: np.ndarray) -> np.ndarray:
        """Values at core and halo vertices; fixed ones are zero."""
        if not len(known):
            return np.zeros(v.shape)
        at = np.minimum(np.searchsorted(known, v), len(known) - 1)
        return np.where(known[at] == v, held[at], 0.0)

    return x, ids, it, float((now / goal) ** 0.5) if goal else 0.0, spent, value_of


def run(rows: DataFrame, g: MeshSpec, local: MeshSpec, n: int = 4, f=None, exact=None, solve: bool = True, tol: float = 1e-10, max_iter: int | None = None, tasks: int | None = None) -> Run:
    """Generate and, if asked, solve and hold against an exact field, in one barrier stage of ``tasks`` tasks (the cluster's slots at most; parts go round)."""
    spark = rows.sparkSession
    tasks = tasks or min(spark.sparkContext.defaultParallelism, rows.agg(F.max("k")).first()[0] + 1)
    placed = rows.select("k", "kind", "a", "b").repartitionById(tasks, F.pmod("k", F.lit(tasks)).cast("int"))
    return Run(store(placed.mapInArrow(lambda it: _task(g, local, n, f, exact, solve, tol, max_iter, it), OUT, barrier=True), "supersteps"))
