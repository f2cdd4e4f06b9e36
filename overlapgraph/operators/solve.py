"""Krylov solvers on DataFrames, a local engine for small systems, and the manufactured problem."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import store
from . import linalg as la
from .assembly import _host, _values, _vertex_ids
from .meshes import MeshSpec

#: The local engine and the dense solver take systems up to this size.
LOCAL_DOFS, LOCAL_ENTRIES = 3_000, 3_000_000


@dataclass
class Solution:
    x: DataFrame
    iterations: int
    residual: float


def diag_scale(k: DataFrame) -> DataFrame:
    """Rows (v, d): the inverse diagonal, independent of any partition."""
    return k.where("i = j").select(F.col("i").alias("v"), (1.0 / F.col("val")).alias("d"))


def _pack(k: DataFrame, f: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    rows = f.orderBy("v").limit(LOCAL_DOFS + 1).toPandas()
    if len(rows) > LOCAL_DOFS:
        raise ValueError(f"the local engine takes at most {LOCAL_DOFS} unknowns")
    if k.limit(LOCAL_ENTRIES + 1).count() > LOCAL_ENTRIES:
        raise ValueError(f"the local engine takes at most {LOCAL_ENTRIES} entries")
    e = k.toPandas()
    ids = rows["v"].to_numpy()
    at = lambda c: np.searchsorted(ids, e[c].to_numpy())
    return ids, at("i"), at("j"), e["val"].to_numpy(float), rows["val"].to_numpy(float)


def _bicgstab(apply, b: np.ndarray, scale: np.ndarray, tol: float, limit: int) -> tuple[np.ndarray, int, float]:
    """Stabilised bi-conjugate gradients on the row-scaled system, from zero."""
    b = scale * b
    x, r = np.zeros_like(b), b.copy()
    shadow, p, v = r.copy(), np.zeros_like(b), np.zeros_like(b)
    rho = alpha = omega = 1.0
    goal = np.linalg.norm(b)
    if goal == 0:
        return x, 0, 0.0
    it = 0
    while it < limit and np.linalg.norm(r) > tol * goal:
        it += 1
        new = shadow @ r
        p = r + (new / rho) * (alpha / omega) * (p - omega * v)
        rho = new
        v = scale * apply(p)
        alpha = rho / (shadow @ v)
        s = r - alpha * v
        t = scale * apply(s)
        tt = t @ t
        omega = (t @ s) / tt if tt else 0.0
        x = x + alpha * p + omega * s
        r = s - omega * t
    return x, it, float(np.linalg.norm(r) / goal)


def solve_local(spark: SparkSession, k: DataFrame, f: DataFrame, tol: float = 1e-10, method: str = "bicgstab") -> Solution:
    """A small system in one place: bicgstab, cg, jacobi or dense."""
    ids, i, j, val, b = _pack(k, f)
    n = len(ids)
    apply = lambda x: np.bincount(i, weights=val * x[j], minlength=n)
    diag = np.bincount(i[i == j], weights=val[i == j], minlength=n)
    if method == "dense":
        a = np.zeros((n, n))
        np.add.at(a, (i, j), val)
        x = np.linalg.solve(a, b)
        it = 0
    elif method == "cg":
        x, r = np.zeros(n), b.copy()
        z = r / diag
        p, it = z.copy(), 0
        while it < n and np.linalg.norm(r) > tol * np.linalg.norm(b):
            it += 1
            q = apply(p)
            step = (r @ z) / (p @ q)
            old = r @ z
            x, r = x + step * p, r - step * q
            z = r / diag
            p = z + (r @ z) / old * p
    elif method == "jacobi":
        x, it = np.zeros(n), 0
        while it < 50 * n and np.linalg.norm(b - apply(x)) > tol * np.linalg.norm(b):
            it += 1
            x = x + 0.5 * (b - apply(x)) / diag
    else:
        x, it, _ = _bicgstab(apply, b, 1.0 / diag, tol, n)
    rel = float(np.linalg.norm(b - apply(x)) / max(np.linalg.norm(b), 1e-300))
    return Solution(spark.createDataFrame(list(zip(ids.tolist(), x.tolist(), strict=True)), "v long, x double"), it, rel)


def bicgstab(kp: DataFrame, f: DataFrame, part: DataFrame, comm: DataFrame, tol: float = 1e-10, max_iter: int | None = None) -> Solution:
    """The distributed loop: part-owned rows that stay where they are, halo-only exchange, core-only dot products.

    One table (v and the loop's vectors) is written to the shared folder twice per iteration, and all scalars of a half
    step come from one aggregation, so an iteration is two sparse products and three small actions.
    """
    scale = kp.where("i = j").select(F.col("i").alias("v"), (1.0 / F.col("val")).alias("d"))
    kp = la.place_parts(store(kp, "solve-matrix"), part.agg(F.max("k")).first()[0] + 1)
    b = f.join(scale, "v").select("v", "d", (F.col("val") * F.col("d")).alias("b"))
    st = store(b.select("v", "d", F.lit(0.0).alias("x"), F.col("b").alias("r"), F.col("b").alias("h"), F.lit(0.0).alias("p"), F.lit(0.0).alias("q")), "solve-state")
    limit = max_iter or st.count()
    goal2 = st.agg(F.sum(F.col("r") * F.col("r"))).first()[0] or 0.0
    rho = alpha = omega = 1.0
    it, rel = 0, 0.0 if goal2 == 0 else 1.0

    def product(name: str) -> DataFrame:
        y = la.spmv_parts(kp, st.select("v", F.col(name).alias("x")), part, comm)
        return y.select("v", F.col("x").alias("y"))

    while goal2 > 0 and it < limit and rel > tol:
        it += 1
        new = st.agg(F.sum(F.col("h") * F.col("r"))).first()[0]
        beta = (new / rho) * (alpha / omega)
        rho = new
        st = st.withColumn("p", F.col("r") + beta * (F.col("p") - omega * F.col("q")))
        st = store(st.join(product("p"), "v").withColumn("q", F.col("d") * F.col("y")).drop("y"), "solve-state")
        alpha = rho / st.agg(F.sum(F.col("h") * F.col("q"))).first()[0]
        st = st.withColumn("s", F.col("r") - alpha * F.col("q"))
        st = store(st.join(product("s"), "v").withColumn("t", F.col("d") * F.col("y")).drop("y"), "solve-state")
        ts, tt = st.agg(F.sum(F.col("t") * F.col("s")), F.sum(F.col("t") * F.col("t"))).first()
        omega = ts / tt if tt else 0.0
        st = st.withColumn("x", F.col("x") + alpha * F.col("p") + omega * F.col("s")).withColumn("r", F.col("s") - omega * F.col("t")).drop("s", "t")
        st = store(st, "solve-state")
        rel = (st.agg(F.sum(F.col("r") * F.col("r"))).first()[0] / goal2) ** 0.5
    kp.unpersist()
    return Solution(st.select("v", "x"), it, rel)


def sine_product(x: np.ndarray) -> np.ndarray:
    """The manufactured solution, a product of full sine waves."""
    return np.prod(np.sin(2 * np.pi * x), axis=-1)


def sine_source(x: np.ndarray) -> np.ndarray:
    return 4 * x.shape[-1] * np.pi**2 * sine_product(x)


def coefficients(x: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    rows = x.orderBy("v").toPandas()
    return rows["v"].to_numpy(), rows["x"].to_numpy(float)


def evaluate(points: DataFrame, g: MeshSpec, local: MeshSpec | None, x: DataFrame) -> DataFrame:
    """Adds ``u`` to rows with a coordinate array ``x``: the sum of both expansions, the local one inside its box.

    Each point names its functions, the coefficients are joined to them and summed back. Coefficients with a column
    ``run`` give each point once for every run.
    """
    run_of = ["run"] if "run" in x.columns else []
    rows = points.withColumn("__at", F.monotonically_increasing_id())
    rows = store(rows, "evaluate-points")

    def run(batches):
        import pyarrow as pa

        for b in batches:
            at = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, g.dim)
            ids = b.column("__at").to_numpy()
            for spec in [g] + ([local] if local else []):
                inside = np.all((at >= np.array(spec.lo) - 1e-12) & (at <= np.array(spec.hi) + 1e-12), axis=1)
                if not inside.any():
                    continue
                host = _host(spec, at[inside])
                v, val = _vertex_ids(spec, host), _values(spec, at[inside], host)[0]
                yield pa.RecordBatch.from_pydict({"__at": np.repeat(ids[inside], v.shape[1]), "v": v.reshape(-1), "n": val.reshape(-1)})

    terms = rows.select("x", "__at").mapInArrow(run, "__at long, v long, n double")
    u = terms.join(x.withColumnRenamed("x", "c"), "v").groupBy("__at", *run_of).agg(F.sum(F.col("n") * F.col("c")).alias("u"))
    return rows.join(u, "__at", "left").withColumn("u", F.coalesce("u", F.lit(0.0))).drop("__at")
