"""Queries on generated meshes, and the same in SQL by another route (index arithmetic, Kronecker products, recursion)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import assembly as asm
from ..operators import basis, geometry, graph, linalg, meshes, metrics, partition, solve, subdomain, supersteps, weights
from ..operators.meshes import MESH_STRIDE, MeshSpec
from ..sources.tables import store
from . import fixtures

G, L = fixtures.grid(5, 3, 4, 0.4)
#: A smaller pair for matrix queries, and one whose meshes are not aligned.
GS, LS = fixtures.grid(3, 2, 2, 1 / 3)
GN, LN = fixtures.grid(5, 3, 5, 0.3)
LINE = MeshSpec("G", "spline", 3, (5,), (0.0,), (1.0,), 0)
N_PARTS = 8

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return put


def _r(c, digits: int = 8):
    return F.round(F.col(c) if isinstance(c, str) else c, digits) + 0.0


# ---- pieces of SQL ---------------------------------------------------------------------------


def sql_digits(col: str, sizes: tuple, names: str) -> str:
    out, stride = [], 1
    for a, n in enumerate(sizes):
        out.append(f"({col} // {stride}) % {n} AS {names}{a}")
        stride *= n
    return ", ".join(out)


def sql_encode(names: str, sizes: tuple, add: int = 0) -> str:
    out, stride = [], 1
    for a, n in enumerate(sizes):
        out.append(f"({names.format(a)}) * {stride}")
        stride *= n
    return " + ".join(out) + (f" + {add}" if add else "")


def sql_vertices(s: MeshSpec, name: str) -> str:
    return f"{name} AS (SELECT range AS id, range + {s.offset} AS v, {sql_digits('range', s.n_cp, 'a')} FROM range({s.n_vertices}))"


def sql_incidence(s: MeshSpec, name: str) -> str:
    m = s.degree + 1
    ids = sql_encode(f"e{{0}} * {s.step} + p{{0}}", s.n_cp, s.offset)
    return (
        f"{name} AS (SELECT e, pos, {ids} AS v FROM (SELECT range AS e, {sql_digits('range', s.n_el, 'e')} FROM range({s.n_elements})), "
        f"(SELECT range AS pos, {sql_digits('range', (m,) * s.dim, 'p')} FROM range({s.n_ldof})))"
    )


def sql_pairs(s: MeshSpec, name: str) -> str:
    """All ordered neighbour pairs of a spline or linear mesh, by index distance."""
    near = " AND ".join(f"abs(x.a{k} - y.a{k}) <= {s.degree}" for k in range(s.dim))
    return f"{name}_v AS (SELECT range + {s.offset} AS v, {sql_digits('range', s.n_cp, 'a')} FROM range({s.n_vertices})), {name} AS (SELECT x.v AS i, y.v AS j FROM {name}_v x JOIN {name}_v y ON {near})"


def sql_between(local: MeshSpec, g: MeshSpec, name: str) -> str:
    """Inter-mesh pairs by comparing support intervals per axis."""
    tests = []
    for k in range(g.dim):
        hl, hg = repr(local.h[k]), repr(g.h[k])
        lo_l, hi_l = f"greatest(l.a{k} - 1, 0) * {hl}", f"least(l.a{k} + 1, {local.n_el[k]}) * {hl}"
        lo_g, hi_g = f"greatest(g.a{k} - {g.degree}, 0) * {hg}", f"least(g.a{k} + 1, {g.n_el[k]}) * {hg}"
        tests.append(f"{lo_l} + 1e-8 < {hi_g} AND {lo_g} + 1e-8 < {hi_l}")
    return (
        f"{name}_l AS (SELECT range + {local.offset} AS v, {sql_digits('range', local.n_cp, 'a')} FROM range({local.n_vertices})), "
        f"{name}_g AS (SELECT range AS v, {sql_digits('range', g.n_cp, 'a')} FROM range({g.n_vertices})), "
        f"{name} AS (SELECT g.v AS i, l.v AS j FROM {name}_g g JOIN {name}_l l ON {' AND '.join(tests)})"
    )


def sql_gauss() -> str:
    a, b = "sqrt(3.0::DOUBLE/7 - 2.0::DOUBLE/7*sqrt(1.2::DOUBLE))", "sqrt(3.0::DOUBLE/7 + 2.0::DOUBLE/7*sqrt(1.2::DOUBLE))"
    wa, wb = "(18 + sqrt(30.0::DOUBLE))/36", "(18 - sqrt(30.0::DOUBLE))/36"
    return f"gauss(q, xi, gw) AS (VALUES (0, -({b}), {wb}), (1, -({a}), {wa}), (2, {a}, {wa}), (3, {b}, {wb}))"


def sql_splines(n: int, p: int, points: str, name: str, lo: float = 0.0, h: float = 1.0) -> str:
    """Spline values and slopes at rows (pt, s, x) of ``points``, by recursion on the knots."""
    knot = lambda i: f"({lo!r}::DOUBLE + least(greatest({i} - {p}, 0), {n}) * {h!r}::DOUBLE)"
    out = [f"{name}_0 AS (SELECT pt, s, x, s + {p} AS i, 1.0::DOUBLE AS n FROM {points})"]
    for d in range(1, p + 1):
        left = f"n * (x - {knot('i')}) / ({knot(f'i + {d}')} - {knot('i')})"
        right = f"n * ({knot(f'i + {d}')} - x) / ({knot(f'i + {d}')} - {knot('i')})"
        out.append(f"{name}_{d} AS (SELECT pt, s, x, i, sum(n) AS n FROM (SELECT pt, s, x, i, {left} AS n FROM {name}_{d - 1} UNION ALL SELECT pt, s, x, i - 1 AS i, {right} AS n FROM {name}_{d - 1}) GROUP BY pt, s, x, i)")
    up = f"{p} * n / ({knot(f'i + {p}')} - {knot('i')})"
    out.append(f"{name}_d AS (SELECT pt, i, sum(g) AS g FROM (SELECT pt, i, {up} AS g FROM {name}_{p - 1} UNION ALL SELECT pt, i - 1 AS i, -({up}) AS g FROM {name}_{p - 1}) GROUP BY pt, i)")
    out.append(f"{name} AS (SELECT b.pt, b.s, b.x, b.i, b.n, d.g FROM {name}_{p} b JOIN {name}_d d ON b.pt = d.pt AND b.i = d.i)")
    # knot number i belongs to function i; the first p knots are repeated, so functions count from 0
    return ", ".join(out)


def sql_hats(n: int, points: str, name: str, h: float) -> str:
    """Linear functions at rows (pt, s, x)."""
    return (
        f"{name} AS (SELECT pt, s, x, s AS i, (s + 1) - x / {h!r} AS n, -1.0::DOUBLE / {h!r} AS g FROM {points} "
        f"UNION ALL SELECT pt, s, x, s + 1 AS i, x / {h!r} - s AS n, 1.0::DOUBLE / {h!r} AS g FROM {points})"
    )


def sql_axis(s: MeshSpec, name: str) -> str:
    """One-dimensional mass and stiffness matrices of an axis (all axes are alike here)."""
    n, h = s.n_el[0], s.h[0]
    pts = f"{name}_p AS (SELECT range * 4 + q AS pt, range AS s, (range + (xi + 1) / 2) * {h!r}::DOUBLE AS x, gw * {h!r} / 2 AS w FROM range({n}), gauss)"
    vals = sql_splines(n, s.degree, f"{name}_p", f"{name}_b", 0.0, h) if s.family == "spline" else sql_hats(n, f"{name}_p", f"{name}_b", h)
    return f"{pts}, {vals}, {name} AS (SELECT a.i, b.i AS j, sum(p.w * a.n * b.n) AS m, sum(p.w * a.g * b.g) AS k FROM {name}_b a JOIN {name}_b b ON a.pt = b.pt JOIN {name}_p p ON p.pt = a.pt GROUP BY a.i, b.i)"


def sql_cross_axis(local: MeshSpec, g: MeshSpec, name: str) -> str:
    """One-dimensional coupling matrices: local points, both bases there."""
    hl, hg = local.h[0], g.h[0]
    pl = f"{name}_p AS (SELECT range * 4 + q AS pt, range AS s, (range + (xi + 1) / 2) * {hl!r}::DOUBLE AS x, gw * {hl!r} / 2 AS w FROM range({local.n_el[0]}), gauss)"
    pg = f"{name}_q AS (SELECT pt, CAST(least(greatest(floor(x / {hg!r} + 1e-8), 0), {g.n_el[0] - 1}) AS BIGINT) AS s, x FROM {name}_p)"
    return (
        f"{pl}, {pg}, {sql_hats(local.n_el[0], f'{name}_p', f'{name}_l', hl)}, {sql_splines(g.n_el[0], g.degree, f'{name}_q', f'{name}_g', 0.0, hg)}, "
        f"{name} AS (SELECT a.i, b.i AS j, sum(p.w * a.n * b.n) AS m, sum(p.w * a.g * b.g) AS k FROM {name}_g a JOIN {name}_l b ON a.pt = b.pt JOIN {name}_p p ON p.pt = a.pt GROUP BY a.i, b.i)"
    )


def sql_kron(axis: str, rows: MeshSpec, cols: MeshSpec) -> str:
    i = sql_encode("{0}.i", rows.n_cp, rows.offset)
    j = sql_encode("{0}.j", cols.n_cp, cols.offset)
    for k, t in enumerate("xyz"):
        i, j = i.replace(f"({k}.i)", f"{t}.i"), j.replace(f"({k}.j)", f"{t}.j")
    return f"SELECT {i} AS i, {j} AS j, x.k*y.m*z.m + x.m*y.k*z.m + x.m*y.m*z.k AS val FROM {axis} x, {axis} y, {axis} z"


def sql_octant(s: MeshSpec, col: str = "x") -> str:
    """Part of a vertex by coordinate halves, from its index digits a0.. (spline: mean knots; linear: nodes)."""
    out = []
    for k in range(s.dim):
        n, p = s.n_el[k], s.degree
        if s.family == "spline":
            x = "(" + " + ".join(f"greatest(0, least({n}, a{k} + {m} - {p}))" for m in range(1, p + 1)) + f") * {s.hi[k]!r}::DOUBLE / {n * p}"
        else:
            x = f"a{k} * {s.hi[k]!r}::DOUBLE / {n * p}"
        out.append(f"CAST(greatest(0, least(1, floor(({x}) / 0.5 + 1e-12))) AS INT) * {2**k}")
    return " + ".join(out)


def sql_parts(g: MeshSpec, local: MeshSpec) -> str:
    return (
        f"{sql_vertices(g, 'gv')}, {sql_vertices(local, 'lv')}, part AS (SELECT v, {sql_octant(g)} AS k FROM gv UNION ALL SELECT v, (v - {local.offset}) % {N_PARTS} AS k FROM lv)"
    )


def sql_edges(g: MeshSpec, local: MeshSpec) -> str:
    return (
        f"{sql_pairs(g, 'gg')}, {sql_pairs(local, 'll')}, {sql_between(local, g, 'gl')}, edges AS (SELECT i, j, 'GG' AS kind FROM gg WHERE i <= j "
        f"UNION ALL SELECT i, j, 'LL' AS kind FROM ll WHERE i <= j UNION ALL SELECT i, j, 'GL' AS kind FROM gl)"
    )


_EXT = """, e2 AS (SELECT i, j FROM edges WHERE i <> j UNION SELECT j AS i, i AS j FROM edges WHERE i <> j),
halo AS (SELECT DISTINCT a.k, e2.j AS v, b.k AS owner FROM e2 JOIN part a ON a.v = e2.i JOIN part b ON b.v = e2.j WHERE a.k <> b.k),
ext AS (SELECT k, v, true AS is_core, k AS owner FROM part UNION ALL SELECT k, v, false, owner FROM halo)"""


def _overlay(spark):
    return graph.graph_overlay(spark, GS, LS)


def _parts(spark) -> DataFrame:
    """A fixed partition for checks: octants for global vertices, ids in turn for local ones."""
    return partition.partition_octant(meshes.vertices(spark, GS)).unionByName(
        meshes.vertices(spark, LS).select("v", ((F.col("v") - LS.offset) % N_PARTS).cast("int").alias("k"))
    )


_SMALL = f"WITH {sql_parts(GS, LS)}, {sql_edges(GS, LS)}{_EXT}"


# ---- the pairs of meshes as sales rows fill them -------------------------------------------------


def sql_sold(g: MeshSpec, local: MeshSpec) -> str:
    """Sales rows with their global element (sr), those of the local box with their element there (sl), filled elements and cells."""
    spans = ", ".join(f"CAST(least(greatest(floor(x{k} / {g.h[k]!r}::DOUBLE + 1e-8), 0), {g.n_el[k] - 1}) AS BIGINT) AS s{k}, CAST(floor(x{k} / {local.h[k]!r}::DOUBLE + 1e-8) AS BIGINT) AS t{k}" for k in range(3))
    e_g, e_l = sql_encode("s{0}", g.n_el), sql_encode("t{0}", local.n_el)
    return (
        f"sr AS (SELECT *, {e_g} AS e_g FROM (SELECT *, {spans} FROM (SELECT l_orderkey, l_linenumber, (l_quantity - 1) / 49 AS x0, l_discount / 0.1 AS x1, l_tax / 0.08 AS x2 FROM lineitem))), "
        f"sl AS (SELECT *, {e_l} AS e_l FROM sr WHERE t0 < {local.n_el[0]} AND t1 < {local.n_el[1]} AND t2 < {local.n_el[2]}), "
        "fg AS (SELECT e_g AS e, count(*) AS n FROM sr GROUP BY e_g), fl AS (SELECT e_l AS e, count(*) AS n FROM sl GROUP BY e_l), cells AS (SELECT e_l, e_g, count(*) AS n_q FROM sl GROUP BY e_l, e_g)"
    )


def sql_sold_overlay(g: MeshSpec, local: MeshSpec) -> str:
    """Incidence of filled elements, the graph by elements and cells, fixed parts and extended sets."""
    return (
        f"WITH {sql_sold(g, local)}, {sql_incidence(g, 'ga')}, {sql_incidence(local, 'la')}, ig AS (SELECT e, v FROM ga WHERE e IN (SELECT e FROM fg)), il AS (SELECT e, v FROM la WHERE e IN (SELECT e FROM fl)), "
        f"edges AS (SELECT DISTINCT a.v AS i, b.v AS j FROM ig a JOIN ig b ON a.e = b.e AND a.v <= b.v UNION ALL SELECT DISTINCT a.v AS i, b.v AS j FROM il a JOIN il b ON a.e = b.e AND a.v <= b.v "
        f"UNION ALL SELECT DISTINCT ig.v AS i, il.v AS j FROM cells JOIN il ON il.e = e_l JOIN ig ON ig.e = e_g), {sql_parts(g, local).replace('part AS', 'everywhere AS')}, "
        f"part AS (SELECT v, k FROM everywhere WHERE v IN (SELECT v FROM ig UNION SELECT v FROM il)){_EXT}"
    )


_SOLD = sql_sold_overlay(GS, LS)


def _sold(spark, sf_dir):
    """(incidence of G, of L, cells, graph, parts) of the small pair as sales rows fill it; the filled elements are counted once and stored."""
    in_g, in_l, cells = (store(t, "sold") for t in fixtures.sold(spark, sf_dir, GS, LS))
    inc_g, inc_l = fixtures.sold_incidence(spark, GS, in_g), fixtures.sold_incidence(spark, LS, in_l)
    edges = graph.graph_from_incidence(inc_g).unionByName(graph.graph_from_incidence(inc_l, "LL")).unionByName(graph.graph_from_cells(cells, inc_l, inc_g))
    used = inc_g.select("v").union(inc_l.select("v")).distinct()
    return (inc_g.join(in_g, "e"), inc_l.join(in_l, "e"), cells, store(edges, "sold-edges"), store(_parts(spark).join(used, "v", "left_semi"), "sold-parts"))


# ---- geometry ----------------------------------------------------------------------------------


def _x(s: MeshSpec, k: int) -> str:
    n, p = s.n_el[k], s.degree
    return "round((" + " + ".join(f"greatest(0, least({n}, a{k} + {m} - {p}))" for m in range(1, p + 1)) + f") * 1.0::DOUBLE / {n * p}, 8)"


@query(f"WITH {sql_vertices(G, 'g')} SELECT v, {_x(G, 0)} AS x0, {_x(G, 1)} AS x1, {_x(G, 2)} AS x2, a0 IN (0, 7) OR a1 IN (0, 7) OR a2 IN (0, 7) AS fixed FROM g")
def grid_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    return meshes.vertices(spark, G).select("v", *[_r(F.col("x")[k]).alias(f"x{k}") for k in range(3)], "fixed")


@query(f"WITH {sql_incidence(L, 'l')} SELECT e, CAST(pos AS INT) AS pos, v FROM l")
def grid_elements(spark, sf_dir):
    return meshes.incidence(spark, L).select("e", "pos", "v")


@query("SELECT CAST(range AS INT) AS i, round(least(greatest(range - 3, 0), 5) * 0.2::DOUBLE, 8) AS knot FROM range(12)")
def knot_vector(spark, sf_dir):
    return meshes.knot_vector(spark, LINE).select("i", _r("knot").alias("knot"))


_DAYS = "k AS (SELECT floor(x) AS d, min(x) AS t FROM (SELECT (epoch_us(ts::TIMESTAMP) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) / 86400000000.0::DOUBLE AS x FROM events) GROUP BY d)"


@query(
    f"WITH {_DAYS}, o AS (SELECT t, copy FROM k, (SELECT unnest([1, 2, 3]) AS copy) WHERE copy = 1 OR t = (SELECT min(t) FROM k) OR t = (SELECT max(t) FROM k)), "
    "r AS (SELECT row_number() OVER w - 1 AS i, (t + lead(t, 1) OVER w + lead(t, 2) OVER w) / 3 AS x FROM o WINDOW w AS (ORDER BY t, copy)) SELECT i, round(x, 8) AS x FROM r WHERE x IS NOT NULL"
)
def control_points(spark, sf_dir):
    """The points of cubic functions on the time axis, whose unequal spans begin with the first event of each day."""
    first = fixtures.event_points(spark, sf_dir).select(F.col("x")[0].alias("t")).groupBy(F.floor("t")).agg(F.min("t").alias("t")).select("t")
    return meshes.greville(first, 3).select("i", _r("x").alias("x"))


def _points(spark, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("pt"), ((F.col("id") + 0.5) / n).alias("x"))


@query(
    "SELECT pt, CAST(a AS INT) AS a, round([1, 3, 3, 1][a + 1] * pow(t, a) * pow(1 - t, 3 - a), 8) + 0.0 AS val FROM (SELECT pt, x - floor(x) AS t FROM "
    "(SELECT event_id AS pt, (epoch_us(ts::TIMESTAMP) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) / 86400000000.0::DOUBLE AS x FROM events)), (SELECT range AS a FROM range(4))"
)
def bernstein_table(spark, sf_dir):
    """Cubic Bernstein functions at every event, in its daily span."""
    pts = fixtures.event_points(spark, sf_dir).select(F.col("event_id").alias("pt"), (F.col("x")[0] - F.floor(F.col("x")[0])).alias("x"))
    b = F.array(*basis.bernstein_expr(F.col("x") * 2 - 1, 3))
    return pts.select("pt", F.posexplode(b).alias("a", "val")).select("pt", "a", _r("val").alias("val"))


@query("SELECT range AS pt, CAST(a AS INT) AS a, round(CASE a WHEN 0 THEN x * (x - 1) / 2 WHEN 1 THEN 1 - x * x ELSE x * (x + 1) / 2 END, 8) AS val FROM (SELECT range, (range + 0.5::DOUBLE) / 40 * 2 - 1 AS x FROM range(40)), (SELECT range AS a FROM range(3))")
def lagrange_table(spark, sf_dir):
    b = F.array(*basis.lagrange_expr(F.col("x") * 2 - 1, 2))
    return _points(spark, 40).select("pt", F.posexplode(b).alias("a", "val")).select("pt", "a", _r("val").alias("val"))


_PTS = "pts AS (SELECT range AS pt, CAST(floor((range + 0.5::DOUBLE) / 40 * 5) AS BIGINT) AS s, (range + 0.5::DOUBLE) / 40 AS x FROM range(40))"
_SPLINES = f"WITH {_PTS}, {sql_splines(5, 3, 'pts', 'b', 0.0, 0.2)} SELECT pt, i, round(n, 8) AS val FROM b"


@query(_SPLINES)
def spline_table_extraction(spark, sf_dir):
    span = F.floor(F.col("x") * 5).cast("int")
    rows = _points(spark, 40).withColumn("span", span).join(F.broadcast(basis.extraction_table(spark, 5, 3)), "span")
    val = basis.spline_expr((F.col("x") * 5 - F.col("span")) * 2 - 1, F.col("c"), 3)
    return rows.select("pt", "span", F.posexplode(val).alias("a", "val")).select("pt", (F.col("span") + F.col("a")).cast("long").alias("i"), _r("val").alias("val"))


@query(_SPLINES)
def spline_table_recursive(spark, sf_dir):
    def run(batches):
        import numpy as np
        import pyarrow as pa

        for b in batches:
            x = b.column("x").to_numpy()
            s = np.floor(x * 5).astype(int)
            val, _ = basis.spline_recursive(x, np.array(meshes.open_knots(0.0, 1.0, 5, 3)), 3, s)
            yield pa.RecordBatch.from_pydict({"pt": np.repeat(b.column("pt").to_numpy(), 4), "i": (s[:, None] + np.arange(4)).reshape(-1), "val": val.reshape(-1)})

    return _points(spark, 40).mapInArrow(run, "pt long, i long, val double").select("pt", "i", _r("val").alias("val"))


@query(f"WITH {sql_gauss()} SELECT q, round(xi, 8) AS xi, round(gw, 8) AS w FROM gauss")
def gauss_points(spark, sf_dir):
    return geometry.gauss_rule(spark, 4, 1).select("q", _r(F.col("xi")[0]).alias("xi"), _r("w").alias("w"))


@query(
    f"WITH {sql_gauss()}, pts AS (SELECT range * 4 + q AS pt, range AS s, (range + (xi + 1) / 2) * 0.2::DOUBLE AS x FROM range(5), gauss), {sql_splines(5, 3, 'pts', 'b', 0.0, 0.2)} "
    "SELECT s AS e, CAST(pt % 4 AS INT) AS q, CAST(i - s AS INT) AS pos, round(n, 7) AS n, round(g, 7) AS g FROM b"
)
def geometric_database_1d(spark, sf_dir):
    db = geometry.geometric_database(spark, LINE, 4)
    return db.select("e", "q", F.posexplode(F.arrays_zip("n", "g")).alias("pos", "z")).select("e", "q", "pos", _r("z.n", 7).alias("n"), _r(F.col("z.g")[0], 7).alias("g"))


_LOC = ", ".join(f"CAST(least(greatest(floor(x{k} / 0.2 + 1e-8), 0), 4) AS BIGINT) AS s{k}" for k in range(3))
_COUPLED = (
    f"WITH {sql_gauss()}, pts AS (SELECT e, a.q + 4 * b.q + 16 * c.q AS q, (e0 + (a.xi + 1) / 2) * 0.06::DOUBLE AS x0, (e1 + (b.xi + 1) / 2) * 0.06::DOUBLE AS x1, (e2 + (c.xi + 1) / 2) * 0.06::DOUBLE AS x2 "
    f"FROM (SELECT range AS e, {sql_digits('range', (5, 5, 5), 'e')} FROM range(125)), gauss a, gauss b, gauss c), loc AS (SELECT *, {_LOC} FROM pts)"
)


@query(f"WITH {sql_sold(GN, LN)} SELECT l_orderkey, l_linenumber, e_l AS e, e_g, round(x0 / 0.2 * 2 - 2 * s0 - 1, 7) + 0.0 AS xi0 FROM sl")
def coupling_map_grid(spark, sf_dir):
    """Sales rows of the local box as its integration points: their elements in both meshes, and where they lie in the global one."""
    return geometry.coupling_map(fixtures.sales_inside(spark, sf_dir, LN), GN).select("l_orderkey", "l_linenumber", "e", "e_g", _r(F.col("xi_g")[0], 7).alias("xi0"))


@query(f"WITH {sql_sold(GN, LN)} SELECT e_l, e_g, n_q FROM cells")
def crossed_elements(spark, sf_dir):
    """Pairs of a local and a global element with a sales row in both."""
    return geometry.crossed_elements(geometry.coupling_map(fixtures.sales_inside(spark, sf_dir, LN), GN))


# ---- graphs ------------------------------------------------------------------------------------


def _graph_query(name: str, s: MeshSpec) -> None:
    def run(spark, sf_dir):
        return graph.graph_structured(spark, s).select("i", "j")

    QUERIES[name] = run
    SQL[name] = f"WITH {sql_pairs(s, 'g')} SELECT i, j FROM g WHERE i <= j"


for _p in (1, 2, 3):
    _graph_query(f"graph_spline_p{_p}", fixtures.grid(4, _p, 2, 0.5)[0])
_graph_query("graph_lagrange", fixtures.grid(2, 1, 5, 0.5)[1])


@query(f"WITH {sql_incidence(MeshSpec('L', 'lagrange', 2, (3, 3), (0.0, 0.0), (1.0, 1.0), 1), 'l')} SELECT DISTINCT a.v AS i, b.v AS j FROM l a JOIN l b ON a.e = b.e AND a.v <= b.v")
def graph_lagrange_order2(spark, sf_dir):
    return graph.graph_structured(spark, MeshSpec("L", "lagrange", 2, (3, 3), (0.0, 0.0), (1.0, 1.0), 1)).select("i", "j")


@query(f"WITH {sql_edges(G, L)} SELECT i, j, kind FROM edges")
def graph_overlay_exact(spark, sf_dir):
    return graph.graph_overlay(spark, G, L)


def _cells(spark, local: MeshSpec, g: MeshSpec) -> DataFrame:
    return geometry.crossed_elements(geometry.coupling_map(geometry.quadrature(spark, local, 4), g))


@query(
    _COUPLED + f", {sql_incidence(LN, 'il')}, {sql_incidence(GN, 'ig')}, cells AS (SELECT DISTINCT e AS e_l, s0 + 5 * s1 + 25 * s2 AS e_g FROM loc) "
    "SELECT DISTINCT ig.v AS i, il.v AS j, 'GL' AS kind FROM cells JOIN il ON il.e = e_l JOIN ig ON ig.e = e_g"
)
def graph_overlay_sampled(spark, sf_dir):
    return graph.graph_from_cells(_cells(spark, LN, GN), meshes.incidence(spark, LN), meshes.incidence(spark, GN))


@query(_SOLD + " SELECT i, j FROM edges UNION SELECT j AS i, i AS j FROM edges")
def candidate_pattern(spark, sf_dir):
    """The pattern of the matrix of elements and cells with sales rows."""
    return graph.candidate_pattern(_sold(spark, sf_dir)[3])


@query(f"WITH {sql_pairs(GS, 'g')} SELECT i, j FROM g WHERE i <= j")
def graph_from_supports(spark, sf_dir):
    """The generic route: a binned join of support boxes."""
    return graph.support_graph(meshes.supports(spark, GS), 0.25)


@query(f"WITH {sql_edges(G, L)} SELECT coalesce(kind, 'all') AS kind, count(*) AS n_edges, count(*) FILTER (WHERE i <> j) AS n_edges_noself, CAST(sum(CASE WHEN i = j THEN 1 ELSE 2 END) AS BIGINT) AS nnz FROM edges GROUP BY ROLLUP (kind)")
def graph_stats_rollup(spark, sf_dir):
    return graph.graph_stats(graph.graph_overlay(spark, G, L))


# ---- weights -----------------------------------------------------------------------------------

_W_CELLS = (
    "cells AS (SELECT l.e AS e_l, g.e AS e_g FROM (SELECT range AS e, {dl} FROM range({nl})) l JOIN (SELECT range AS e, {dg} FROM range({ng})) g ON {meet})"
).format(
    dl=sql_digits("range", LN.n_el, "b"), dg=sql_digits("range", GN.n_el, "c"), nl=LN.n_elements, ng=GN.n_elements,
    meet=" AND ".join(f"b{k} * 0.06::DOUBLE + 1e-8 < (c{k} + 1) * 0.2::DOUBLE AND c{k} * 0.2::DOUBLE + 1e-8 < (b{k} + 1) * 0.06::DOUBLE" for k in range(3)),
)
_W = (
    f"WITH {sql_incidence(LN, 'il')}, {sql_incidence(GN, 'ig')}, {_W_CELLS}, m AS (SELECT e_l, count(*) AS m FROM cells GROUP BY e_l), "
    "cost AS (SELECT e_l, e_g, 64.0::DOUBLE * 8 * 64 / m AS c FROM cells JOIN m USING (e_l)), "
    "rows AS (SELECT v, 64.0::DOUBLE * 64 * 64 / 64 AS gg, 0.0::DOUBLE AS ll, 0.0::DOUBLE AS c FROM ig UNION ALL SELECT v, 0, 64.0::DOUBLE * 8 * 8 / 8, 0 FROM il "
    "UNION ALL SELECT ig.v, 0, 0, c / 2 / 64 FROM cost JOIN ig ON ig.e = e_g UNION ALL SELECT il.v, 0, 0, c / 2 / 8 FROM cost JOIN il ON il.e = e_l), "
    "w AS (SELECT v, sum(gg) AS gg, sum(ll) AS ll, sum(c) AS c FROM rows GROUP BY v) "
)


def _components(spark) -> DataFrame:
    return weights.weight_components(meshes.incidence(spark, GN), meshes.incidence(spark, LN), geometry.crossed_by_overlap(spark, LN, GN), 64)


@query(_W + "SELECT v, round(gg, 4) AS w_gg, round(ll, 4) AS w_ll, round(c, 4) AS w_c FROM w")
def vertex_weights_grid(spark, sf_dir):
    return _components(spark).select("v", *[_r(c, 4).alias(c) for c in ("w_gg", "w_ll", "w_c")])


@query(_W + "SELECT a.alpha3, v, round(gg + ll + a.alpha3 * c, 4) AS w FROM w, (VALUES (20.0::DOUBLE), (40.0), (60.0), (80.0)) a(alpha3)")
def weight_alpha_sweep(spark, sf_dir):
    return weights.alpha_sweep(_components(spark)).select("alpha3", "v", _r("w", 4).alias("w"))


@query(f"SELECT {125 * 64 * 64 * 64}.0::DOUBLE AS v_gg, {125 * 64 * 8 * 8}.0::DOUBLE AS v_ll, {125 * 64 * 8 * 64}.0::DOUBLE AS v_c, {125 * 64 * 64 * 64}.0::DOUBLE AS e_gg, {125 * 64 * 8 * 8}.0::DOUBLE AS e_ll, {125 * 64 * 8 * 64}.0::DOUBLE AS e_c")
def weight_conservation(spark, sf_dir):
    out = weights.weight_audit(_components(spark), meshes.incidence(spark, GN), meshes.incidence(spark, LN), geometry.crossed_by_overlap(spark, LN, GN), 64)
    return out.select(*[_r(c, 3).alias(c) for c in out.columns])


# ---- partitions and subdomains ------------------------------------------------------------------


@query(_SMALL + " SELECT v, CAST(k AS INT) AS k FROM part")
def partition_octant(spark, sf_dir):
    return _parts(spark)


@query(f"WITH {sql_vertices(G, 'g')} SELECT v, CAST((v % 1000003 * 7919 + 12345) % 1000003 % 8 AS INT) AS k FROM g")
def partition_hash(spark, sf_dir):
    return partition.partition_hash(meshes.vertices(spark, G), 8)


@query(f"WITH {sql_vertices(G, 'g')} SELECT v, CAST(v * 8 // 512 AS INT) AS k FROM g")
def partition_block(spark, sf_dir):
    return partition.partition_block(meshes.vertices(spark, G), 8)


def _sql_morton() -> str:
    parts = []
    for k in range(3):
        x = "(" + " + ".join(f"greatest(0, least(5, a{k} + {m} - 3))" for m in (1, 2, 3)) + ") * 1.0::DOUBLE / 15"
        cell = f"CAST(greatest(0, least(15, floor({x} * 16))) AS BIGINT)"
        parts += [f"((({cell} >> {b}) & 1) << {3 * b + k})" for b in range(4)]
    return " | ".join(parts)


@query(f"WITH {sql_vertices(G, 'g')}, o AS (SELECT v, row_number() OVER (ORDER BY {_sql_morton()}, v) - 1 AS r FROM g) SELECT v, CAST(floor((r + 0.5::DOUBLE) * 8 / 512) AS INT) AS k FROM o")
def partition_curve(spark, sf_dir):
    v = meshes.vertices(spark, G)
    return partition.partition_curve(v, weights.uniform_weights(v), 8, [0.0] * 3, [1.0] * 3, bits=4)


@query()
def partition_hilbert(spark, sf_dir):
    v = meshes.vertices(spark, G)
    return partition.partition_curve(v, weights.uniform_weights(v), 8, [0.0] * 3, [1.0] * 3, curve="hilbert", bits=4)


@query()
def partition_rcb(spark, sf_dir):
    v = meshes.vertices(spark, GN).unionByName(meshes.vertices(spark, LN))
    return partition.partition_rcb(v, weights.combine(_components(spark), (1.0, 1.0, 40.0)), 8)


@query(
    _SOLD + ", r AS (SELECT v, n FROM ig JOIN fg USING (e) UNION ALL SELECT v, n FROM il JOIN fl USING (e)), w AS (SELECT k, count(DISTINCT v) AS n, sum(n) * 1.0::DOUBLE AS w FROM r JOIN part USING (v) GROUP BY k) "
    "SELECT CAST(k AS INT) AS k, n, w, round(w / (sum(w) OVER () / 8), 8) AS share, w <= 1.03 * (sum(w) OVER () / 8) AND w >= (sum(w) OVER () / 8) / 1.03 AS within FROM w"
)
def balance_report(spark, sf_dir):
    """Balance of fixed parts where a vertex weighs as many sales rows as its elements hold."""
    inc_g, inc_l, _, _, p = _sold(spark, sf_dir)
    w = inc_g.select("v", "n").union(inc_l.select("v", "n")).groupBy("v").agg(F.sum("n").cast("double").alias("w"))
    return partition.balance(w, p, N_PARTS).select("k", "n", "w", _r("share").alias("share"), "within")


@query(_SMALL + " SELECT count(*) AS n_edges, count(*) FILTER (WHERE a.k <> b.k) AS cut FROM edges JOIN part a ON a.v = i JOIN part b ON b.v = j WHERE i <> j")
def cut_size(spark, sf_dir):
    return partition.cut_size(_overlay(spark), _parts(spark))


@query(_SMALL + " SELECT count(*) AS n_edges, count(*) FILTER (WHERE a.k <> b.k) AS cut FROM edges JOIN part a ON a.v = i JOIN part b ON b.v = j WHERE i <> j AND kind <> 'GL'")
def per_mesh_cut(spark, sf_dir):
    """The cut that a partition of separate meshes sees: edges between the meshes are missing."""
    return partition.cut_size(graph.graph_without_coupling(_overlay(spark)), _parts(spark))


@query(_SMALL + " SELECT CAST(k AS INT) AS k, v, CAST(owner AS INT) AS owner FROM halo")
def halo(spark, sf_dir):
    return subdomain.halo(_overlay(spark), _parts(spark))


@query(_SMALL + " SELECT CAST(k AS INT) AS k, v, is_core, CAST(owner AS INT) AS owner FROM ext")
def extended_sets(spark, sf_dir):
    return subdomain.extended_sets(_overlay(spark), _parts(spark))


@query(_SMALL + " SELECT CAST(a.k AS INT) AS k, count(*) AS n_edges FROM edges JOIN ext a ON a.v = i JOIN ext b ON b.v = j AND a.k = b.k GROUP BY a.k")
def extended_subgraph(spark, sf_dir):
    e = _overlay(spark)
    return subdomain.extended_subgraph(e, subdomain.extended_sets(e, _parts(spark))).groupBy("k").agg(F.count(F.lit(1)).alias("n_edges"))


_ASSIGN = f", {sql_incidence(GS, 'ig')}, {sql_incidence(LS, 'il')}"


@query(_SOLD + " SELECT e, CAST(k AS INT) AS k, count(*) FILTER (WHERE is_core) AS n_core, any_value(n) AS n_rows FROM ig JOIN ext USING (v) JOIN fg USING (e) GROUP BY e, k HAVING count(*) = 27")
def assign_containment(spark, sf_dir):
    """Global elements with sales rows, the parts that hold all their vertices, and the rows in them."""
    inc_g, _, _, e, p = _sold(spark, sf_dir)
    return subdomain.assign_elements(inc_g, subdomain.extended_sets(e, p)).join(inc_g.select("e", F.col("n").alias("n_rows")).distinct(), "e").select("e", "k", "n_core", "n_rows")


@query(_SOLD + " SELECT e, CAST(k AS INT) AS k, count(*) FILTER (WHERE is_core) AS n_core, any_value(n) AS n_rows FROM il JOIN ext USING (v) JOIN fl USING (e) GROUP BY e, k HAVING count(*) = 8 AND count(*) FILTER (WHERE is_core) > 0")
def assign_owner(spark, sf_dir):
    """Local elements with sales rows, the parts that own some and hold all of their vertices, and the rows in them."""
    _, inc_l, _, e, p = _sold(spark, sf_dir)
    return subdomain.assign_elements(inc_l, subdomain.extended_sets(e, p), "owner").join(inc_l.select("e", F.col("n").alias("n_rows")).distinct(), "e").select("e", "k", "n_core", "n_rows")


_CELLS_S = (
    "cells AS (SELECT l.e AS e_l, g.e AS e_g FROM (SELECT range AS e, {dl} FROM range({nl})) l JOIN (SELECT range AS e, {dg} FROM range({ng})) g ON {meet})"
).format(
    dl=sql_digits("range", LS.n_el, "b"), dg=sql_digits("range", GS.n_el, "c"), nl=LS.n_elements, ng=GS.n_elements,
    meet=" AND ".join(f"b{k} * {LS.h[0]!r} + 1e-8 < (c{k} + 1) * {GS.h[0]!r} AND c{k} * {GS.h[0]!r} + 1e-8 < (b{k} + 1) * {LS.h[0]!r}" for k in range(3)),
)


@query(
    _SOLD + ", ci AS (SELECT e_l, e_g, il.v FROM cells JOIN il ON il.e = e_l UNION SELECT e_l, e_g, ig.v FROM cells JOIN ig ON ig.e = e_g) "
    "SELECT e_l, e_g, CAST(k AS INT) AS k, count(*) FILTER (WHERE is_core) AS n_core, any_value(n_q) AS n_rows FROM ci JOIN ext USING (v) JOIN cells USING (e_l, e_g) GROUP BY e_l, e_g, k HAVING count(*) = 35"
)
def assign_cells(spark, sf_dir):
    """Cells with sales rows, the parts that hold all vertices of both elements, and the rows in them."""
    inc_g, inc_l, cells, e, p = _sold(spark, sf_dir)
    return subdomain.assign_cells(cells, inc_l, inc_g, subdomain.extended_sets(e, p)).join(cells.withColumnRenamed("n_q", "n_rows"), ["e_l", "e_g"]).select("e_l", "e_g", "k", "n_core", "n_rows")


@query(_SOLD + " SELECT CAST(k AS INT) AS k_to, count(DISTINCT owner) AS n_neighbours, count(*) AS n_values FROM halo GROUP BY k")
def comm_plan(spark, sf_dir):
    """What each part receives, on the graph of elements and cells with sales rows."""
    _, _, _, e, p = _sold(spark, sf_dir)
    return subdomain.comm_summary(subdomain.comm_plan(subdomain.halo(e, p)))


@query("SELECT 0 AS missing_elements, 0 AS missing_cells")
def row_completeness(spark, sf_dir):
    """Elements and cells with a core vertex that their part does not evaluate: there must be none."""
    part, e = _parts(spark), _overlay(spark)
    ext = subdomain.extended_sets(e, part)
    inc_g, inc_l = meshes.incidence(spark, GS), meshes.incidence(spark, LS)
    miss = subdomain.missing_rows(inc_g, part, subdomain.assign_elements(inc_g, ext)).agg(F.count(F.lit(1)).cast("int").alias("missing_elements"))
    ci = subdomain.cell_incidence(geometry.crossed_by_overlap(spark, LS, GS), inc_l, inc_g)
    cells = subdomain.missing_rows(ci, part, subdomain.assign_elements(ci, ext)).agg(F.count(F.lit(1)).cast("int").alias("missing_cells"))
    return miss.crossJoin(cells)


def _layers(n: int) -> str:
    return " UNION ALL ".join(f"SELECT {p} AS p, CAST({n}*{n}*{n} - ({n} - {p}) * ({n} - {p}) * ({n} - {p}) AS BIGINT) AS shared, {p} AS layers" for p in (1, 2, 3))


#: Elements on each axis in the published picture of degree generality.
N_LAYERS = 20


@query(_layers(N_LAYERS))
def shared_layers(spark, sf_dir):
    """Degree generality: eight octants of one spline mesh share p layers of elements at each cut."""
    out = []
    for p in (1, 2, 3):
        s = MeshSpec("G", "spline", p, (N_LAYERS,) * 3, (0.0,) * 3, (1.0,) * 3, 0)
        ix = meshes.digits("v", s.n_cp)
        # owners by index halves: the cut runs between two vertices on every axis
        part = meshes.vertices(spark, s).select("v", reduce(lambda a, b: a + b, [F.when(c >= (N_LAYERS + p) // 2, 2**k).otherwise(0) for k, c in enumerate(ix)]).alias("k"))
        ext = store(subdomain.extended_sets(graph.graph_structured(spark, s), part), "layers")
        owned = subdomain.assign_elements(meshes.incidence(spark, s), ext, "owner")
        shared = subdomain.shared_elements(owned)
        row = meshes.digits("e", s.n_el)
        lone = shared.select(F.col("e"), row[0].alias("a"), row[1].alias("b"), row[2].alias("c"))
        out.append(lone.agg(F.lit(p).alias("p"), F.count(F.lit(1)).alias("shared"), F.countDistinct(F.when((F.col("b") == 0) & (F.col("c") == 0), F.col("a"))).cast("int").alias("layers")))
    return reduce(DataFrame.unionByName, out)


# ---- matrices ----------------------------------------------------------------------------------


@query(f"WITH {sql_gauss()}, {sql_axis(GS, 'ax')}, r AS ({sql_kron('ax', GS, GS)}) SELECT i, j, round(val, 8) + 0.0 AS val FROM r")
def k_gg(spark, sf_dir):
    return asm.k_own(spark, GS).select("i", "j", _r("val").alias("val"))


@query(SQL["k_gg"])
def k_gg_structured(spark, sf_dir):
    return asm.k_structured(spark, GS).select("i", "j", _r("val").alias("val"))


@query(f"WITH {sql_gauss()}, {sql_axis(LS, 'ax')}, r AS ({sql_kron('ax', LS, LS)}) SELECT i, j, round(val, 8) + 0.0 AS val FROM r")
def k_ll(spark, sf_dir):
    return asm.k_own(spark, LS).select("i", "j", _r("val").alias("val"))


_KGL = f"WITH {sql_gauss()}, {sql_cross_axis(LS, GS, 'ax')}, r AS ({sql_kron('ax', GS, LS)})"


@query(_KGL + " SELECT i, j, round(val, 8) + 0.0 AS val FROM r")
def k_gl(spark, sf_dir):
    return asm.k_coupling(spark, LS, GS).select("i", "j", _r("val").alias("val"))


@query(_KGL + " SELECT j AS i, i AS j, round(val, 8) + 0.0 AS val FROM r")
def k_lg(spark, sf_dir):
    return asm.transpose(asm.k_coupling(spark, LS, GS)).select("i", "j", _r("val").alias("val"))


@query(
    f"WITH {sql_gauss()}, {sql_axis(GS, 'ag')}, {sql_axis(LS, 'al')}, {sql_cross_axis(LS, GS, 'ac')}, gg AS ({sql_kron('ag', GS, GS)}), ll AS ({sql_kron('al', LS, LS)}), gl AS ({sql_kron('ac', GS, LS)}), "
    "s AS (SELECT 'GG' AS blk, val FROM gg UNION ALL SELECT 'LL', val FROM ll UNION ALL SELECT 'GL', val FROM gl UNION ALL SELECT 'LG', val FROM gl) "
    "SELECT blk, count(*) AS nnz, round(sum(abs(val)), 6) AS mass, round(sum(val), 6) + 0.0 AS total FROM s GROUP BY blk"
)
def k_block(spark, sf_dir):
    k = asm.block_system(asm.k_own(spark, GS), asm.k_coupling(spark, LS, GS), asm.k_own(spark, LS))
    return k.groupBy("blk").agg(F.count(F.lit(1)).alias("nnz"), _r(F.sum(F.abs("val")), 6).alias("mass"), _r(F.sum("val"), 6).alias("total"))


def _owned(spark) -> tuple[DataFrame, DataFrame]:
    part, e = _parts(spark), _overlay(spark)
    ext = subdomain.extended_sets(e, part)
    assigned = subdomain.assign_elements(meshes.incidence(spark, GS), ext)
    return asm.assemble_owned(assigned, asm.own_block(GS, 4, "laplace"), part, N_PARTS), part


@query(f"WITH {sql_gauss()}, {sql_axis(GS, 'ax')}, r AS ({sql_kron('ax', GS, GS)}), {sql_parts(GS, LS)} SELECT CAST(k AS INT) AS k, i, j, round(val, 8) + 0.0 AS val FROM r JOIN part ON part.v = r.i")
def owned_assembly(spark, sf_dir):
    """Every part evaluates its own elements and keeps its rows; the sum must be the whole matrix."""
    return _owned(spark)[0].select("k", "i", "j", _r("val").alias("val"))


@query(
    f"WITH {sql_gauss()}, p AS (SELECT range * 4 + q AS pt, range AS s, (range + (xi + 1) / 2) * {GS.h[0]!r}::DOUBLE AS x, gw * {GS.h[0]!r} / 2 AS w FROM range({GS.n_el[0]}), gauss), {sql_splines(GS.n_el[0], GS.degree, 'p', 'b', 0.0, GS.h[0])}, "
    "f AS (SELECT i, sum(w * n * sin(2 * pi() * p.x)) AS f FROM b JOIN p ON p.pt = b.pt GROUP BY i) "
    f"SELECT {sql_encode('{0}', GS.n_cp).replace('(0)', 'x.i').replace('(1)', 'y.i').replace('(2)', 'z.i')} AS v, round(12 * pi() * pi() * x.f * y.f * z.f, 8) + 0.0 AS val FROM f x, f y, f z"
)
def rhs_mms(spark, sf_dir):
    return asm.rhs(spark, GS, solve.sine_source).select("v", _r("val").alias("val"))


# ---- vectors -----------------------------------------------------------------------------------


def _vec(spark, s: MeshSpec, a: int) -> DataFrame:
    return meshes.vertices(spark, s).select("v", ((F.col("v") * a % 17) / 17).alias("x"))


@query(f"SELECT range AS v, round(2 * (range * 3 % 17) / 17.0::DOUBLE - 0.5 * (range * 5 % 17) / 17.0::DOUBLE, 8) + 0.0 AS x FROM range({GS.n_vertices})")
def lincomb_parts(spark, sf_dir):
    return linalg.lincomb(2.0, _vec(spark, GS, 3), -0.5, _vec(spark, GS, 5)).select("v", _r("x").alias("x"))


@query(f"WITH {sql_parts(GS, LS)} SELECT CAST(k AS INT) AS k, round(sum((v * 3 % 17) / 17.0::DOUBLE * (v * 5 % 17) / 17.0::DOUBLE), 8) AS dot FROM part WHERE v < {MESH_STRIDE} GROUP BY k")
def dot_parts(spark, sf_dir):
    return linalg.dot_parts(_vec(spark, GS, 3), _vec(spark, GS, 5), _parts(spark)).select("k", _r("dot").alias("dot"))


_SPMV = f"WITH {sql_gauss()}, {sql_axis(GS, 'ax')}, r AS ({sql_kron('ax', GS, GS)}) SELECT i AS v, round(sum(val * (j * 3 % 17) / 17.0::DOUBLE), 7) + 0.0 AS x FROM r GROUP BY i"


@query(_SPMV)
def spmv_naive(spark, sf_dir):
    return linalg.spmv(asm.k_structured(spark, GS), _vec(spark, GS, 3)).select("v", _r("x", 7).alias("x"))


@query(_SPMV)
def spmv_parts(spark, sf_dir):
    kp, part = _owned(spark)
    comm = subdomain.comm_plan(subdomain.halo(graph.graph_structured(spark, GS), part.where(F.col("v") < MESH_STRIDE)))
    return linalg.spmv_parts(kp, _vec(spark, GS, 3), part, comm).select("v", _r("x", 7).alias("x"))


# ---- solver and models ------------------------------------------------------------------------


def system(spark: SparkSession, g: MeshSpec, local: MeshSpec, n: int = 4) -> tuple[DataFrame, DataFrame]:
    """Matrix and right-hand side of the manufactured problem, boundary values eliminated.

    The exact solution is zero on the outer boundary, so the boundary values of both meshes are zero.
    """
    k = asm.block_system(asm.k_own(spark, g, n), asm.k_coupling(spark, local, g, n), asm.k_own(spark, local, n))
    f = asm.rhs(spark, g, solve.sine_source, n).unionByName(asm.rhs(spark, local, solve.sine_source, n))
    fixed = meshes.vertices(spark, g).unionByName(meshes.vertices(spark, local)).where("fixed").select("v", F.lit(0.0).alias("value"))
    return asm.apply_dirichlet(k.select("i", "j", "val"), f, fixed)


def error_of(spark: SparkSession, g: MeshSpec, local: MeshSpec, x: DataFrame, n: int = 4) -> DataFrame:
    """The error measure over the global points outside the local box and the local points inside it."""
    side = local.hi[0]
    inside = reduce(lambda a, b: a & b, [F.col("x")[k] < side for k in range(3)])
    pts = geometry.quadrature(spark, g, n).where(~inside).select("x", "w").unionByName(geometry.quadrature(spark, local, n).select("x", "w"))
    exact = reduce(lambda a, b: a * b, [F.sin(F.col("x")[k] * (2 * 3.141592653589793)) for k in range(3)])
    found = solve.evaluate(pts, g, local, x).withColumn("exact", exact)
    return metrics.l2_error(found.groupBy("run") if "run" in x.columns else found, inside)


@query()
def solve_mms(spark, sf_dir):
    k, f = system(spark, G, L)
    s = solve.solve_local(spark, k, f)
    return error_of(spark, G, L, s.x).withColumn("iterations", F.lit(s.iterations)).withColumn("residual", F.lit(s.residual))


@query()
def solve_mms_parts(spark, sf_dir):
    """The overlaid system by the distributed loop on rows that four parts own; CG and Jacobi of the local engine beside it."""
    k, f = (store(t, "mms-parts") for t in system(spark, GS, LS))
    part = store(partition.partition_hash(f.select("v"), 4), "mms-parts")
    comm = store(subdomain.comm_plan(subdomain.halo(k.where("i <= j").select("i", "j"), part)), "mms-parts")
    runs = [("bicgstab", "parts", solve.bicgstab(linalg.owned_rows(k, part), f, part, comm))]
    runs += [(m, "local", solve.solve_local(spark, k, f, method=m)) for m in ("cg", "jacobi")]
    out = [error_of(spark, GS, LS, s.x).select(F.lit(m).alias("method"), F.lit(e).alias("engine"), "error", F.lit(s.iterations).alias("iterations"), F.lit(s.residual).alias("residual")) for m, e, s in runs]
    return reduce(DataFrame.unionByName, out)


def _model(spark) -> DataFrame:
    """Modelled costs of parts by owned rows on the fixed hash partition, for uniform reading in SQL."""
    comp = _components(spark)
    return metrics.part_costs_owned(comp, partition.partition_hash(comp.select("v"), N_PARTS))


_MODEL = _W + ", c AS (SELECT CAST((v % 1000003 * 7919 + 12345) % 1000003 % 8 AS INT) AS k, sum(gg) AS gg, sum(ll) AS ll, sum(40 * c) AS gl FROM w GROUP BY 1), o AS (SELECT *, gg + ll + gl AS own, max(gg + ll + gl) OVER () AS top FROM c) "


@query(_MODEL + "SELECT k, round(gg, 2) AS gg, round(ll, 2) AS ll, round(gl, 2) AS gl FROM c")
def model_cost(spark, sf_dir):
    return _model(spark).select("k", *[_r(c, 2).alias(c) for c in ("gg", "ll", "gl")])


@query(_MODEL + "SELECT k, round(own, 2) AS own, round(top - own, 2) + 0.0 AS wait, round(top, 2) AS total FROM o")
def model_wait(spark, sf_dir):
    return metrics.with_wait(_model(spark)).select("k", *[_r(c, 2).alias(c) for c in ("own", "wait", "total")])


@query(_MODEL + "SELECT count(*) AS n_dom_used, round(max(own), 2) AS makespan, round(sum(own) / max(own), 6) AS speedup, round(sum(top - own) / sum(top), 6) AS idle FROM o")
def model_speedup(spark, sf_dir):
    comp = _components(spark)
    serial = comp.agg(F.sum(F.col("w_gg") + F.col("w_ll") + 40 * F.col("w_c"))).first()[0]
    out = metrics.model_summary(_model(spark), serial)
    return out.select("n_dom_used", _r("makespan", 2).alias("makespan"), _r("speedup", 6).alias("speedup"), _r("idle", 6).alias("idle"))


_TIMES = "t(n_dom, alpha3, total) AS (VALUES " + ", ".join(
    [f"({n}, 0, {t}::DOUBLE)" for n, _, _, t in metrics.TIMES_UNIFORM] + [f"({n}, {a}, {t}::DOUBLE)" for n, *ts in metrics.TIMES_WEIGHTED for a, t in zip((20, 40, 60, 80), ts, strict=True)]
) + ")"


@query(f"WITH {_TIMES} SELECT t.n_dom, t.alpha3, t.total, round(1358.3 / t.total, 6) AS speedup, round(1358.3 / t.total / t.n_dom * 100, 6) AS efficiency, round(u.total / t.total, 6) AS gain FROM t JOIN t u ON u.n_dom = t.n_dom AND u.alpha3 = 0")
def published_times_derived(spark, sf_dir):
    return metrics.speedups(metrics.published_times(spark)).select("n_dom", "alpha3", "total", *[_r(c, 6).alias(c) for c in ("speedup", "efficiency", "gain")])


def scaling_sweep(spark: SparkSession, g: MeshSpec, local: MeshSpec, parts=(8, 32), third=(None, 20.0, 40.0, 60.0, 80.0), true=(1.0, 1.0, 40.0)) -> DataFrame:
    """Rows (n_dom, alpha3, makespan, speedup, idle, wait): the weighting experiment by owned rows; alpha3 0 is uniform."""
    from ..sources.tables import store

    comp = store(weights.weight_components(meshes.incidence(spark, g), meshes.incidence(spark, local), geometry.crossed_by_overlap(spark, local, g), 64), "sweep")
    serial = comp.agg(F.sum(F.col("w_gg") * true[0] + F.col("w_ll") * true[1] + F.col("w_c") * true[2])).first()[0]
    v = store(meshes.vertices(spark, g).unionByName(meshes.vertices(spark, local)), "sweep-v")
    runs = []
    for n in parts:
        for a in third:
            w = weights.uniform_weights(v) if a is None else weights.combine(comp, (1.0, 1.0, a))
            cost = metrics.part_costs_owned(comp, partition.partition_rcb(v, w, n), true)
            runs.append(cost.select(F.lit(n).alias("n_dom"), F.lit(float(a or 0)).alias("alpha3"), "k", "gg", "ll", "gl"))
    return metrics.model_summary(reduce(DataFrame.unionByName, runs), serial, "n_dom", "alpha3")


@query()
def weighting_experiment(spark, sf_dir):
    return scaling_sweep(spark, *fixtures.grid(10, 3, 10, 0.2), parts=(8,))


# ---- the published mesh pair at full size -----------------------------------------------------------

#: The published pair: 50 cubic spans and 25 linear elements per axis, the local box a tenth of the side.
MESH1 = fixtures.grid(50, 3, 25, 0.1)


@query("SELECT * FROM (VALUES ('GG', CAST(46268279 AS BIGINT)), ('LL', CAST(438976 AS BIGINT)), ('GL', CAST(1259712 AS BIGINT))) t(kind, n)")
def mesh1_graph(spark, sf_dir):
    """Ordered neighbour pairs of the full-size overlay, by kind (pairs between meshes once)."""
    e = graph.graph_overlay(spark, *MESH1)
    return e.groupBy("kind").agg(F.sum(F.when((F.col("i") == F.col("j")) | (F.col("kind") == "GL"), 1).otherwise(2)).alias("n"))


@query("SELECT CAST(166453 AS BIGINT) AS n, 32768000000.0::DOUBLE AS gg, 64000000.0::DOUBLE AS ll, 512000000.0::DOUBLE AS c")
def mesh1_weights(spark, sf_dir):
    """Sums of the full-size weight components: the operation counts of generation."""
    g, local = MESH1
    w = weights.weight_components(meshes.incidence(spark, g), meshes.incidence(spark, local), geometry.crossed_by_overlap(spark, local, g), 64)
    return w.agg(F.count(F.lit(1)).alias("n"), _r(F.sum("w_gg"), 0).alias("gg"), _r(F.sum("w_ll"), 0).alias("ll"), _r(F.sum("w_c"), 0).alias("c"))


@query("SELECT * FROM (VALUES ('GG', CAST(46268279 AS BIGINT)), ('LL', CAST(438976 AS BIGINT)), ('GL', CAST(1259712 AS BIGINT))) t(blk, nnz)")
def mesh1_matrix(spark, sf_dir):
    """All blocks of the full-size matrix: the own blocks from axis matrices, the coupling by quadrature; entries are counted and their row sums vanish."""
    g, local = MESH1
    blocks = [("GG", asm.k_structured(spark, g)), ("LL", asm.k_structured(spark, local)), ("GL", asm.k_coupling(spark, local, g))]
    out = [k.agg(F.lit(n).alias("blk"), F.count("val").alias("nnz"), F.sum("val").alias("s")).where("abs(s) < 1e-6").select("blk", "nnz") for n, k in blocks]
    return reduce(DataFrame.unionByName, out)


def _form(axis: str) -> str:
    """Sums over one axis of its mass and stiffness with the fixed vector (1 + index mod 7) / 7 on both sides, and the pairs."""
    u = "(1 + i % 7) / 7.0::DOUBLE * (1 + j % 7) / 7.0::DOUBLE"
    return f"SELECT sum(m * {u}) AS m, sum(k * {u}) AS k, count(*) AS n FROM {axis}"


def _forms(g: MeshSpec, local: MeshSpec) -> str:
    """Counts and bilinear forms of all blocks from one-dimensional matrices, as products over the axes."""
    named = (("GG", "ag"), ("LL", "al"), ("GL", "ac"), ("LG", "ac"))
    one = " UNION ALL ".join(f"SELECT '{n}' AS blk, CAST(n * n * n AS BIGINT) AS nnz, round(3 * k * m * m, 8) + 0.0 AS form FROM ({_form(a)})" for n, a in named)
    return f"WITH {sql_gauss()}, {sql_axis(g, 'ag')}, {sql_axis(local, 'al')}, {sql_cross_axis(local, g, 'ac')} {one}"


def curve_parts(spark: SparkSession, g: MeshSpec, local: MeshSpec, weight: DataFrame | None = None, n: int = 256) -> DataFrame:
    """Runs of equal weight along a curve through the vertices of both meshes; n / m neighbouring parts make one of m."""
    v = meshes.vertices(spark, g).unionByName(meshes.vertices(spark, local))
    return store(partition.partition_curve(v, weights.uniform_weights(v) if weight is None else weight, n, list(g.lo), list(g.hi)), "curve-parts")


def _mesh1_components(spark) -> DataFrame:
    g, local = MESH1
    return store(weights.weight_components(meshes.incidence(spark, g), meshes.incidence(spark, local), geometry.crossed_by_overlap(spark, local, g), 64), "mesh1-components")


def mesh1_work(spark: SparkSession, n_dom: int = 8) -> DataFrame:
    """What each part of the full-size pair evaluates; parts by a curve, with the published best coefficient."""
    g, local = MESH1
    part = curve_parts(spark, g, local, weights.combine(_mesh1_components(spark), (1.0, 1.0, 40.0)), n_dom)
    return supersteps.work(spark, g, local, geometry.crossed_by_overlap(spark, local, g), part)


@query(_forms(*MESH1))
def mesh1_generation(spark, sf_dir):
    """The published generation: every block of the full-size pair by quadrature on every element, by eight parts that each evaluate
    all elements of their rows; entries and a bilinear form of each block, summed over the parts."""
    run = supersteps.run(mesh1_work(spark), *MESH1, solve=False)
    return run.blocks.groupBy(F.col("name").alias("blk")).agg(F.sum("nnz").alias("nnz"), _r(F.sum("form")).alias("form"))


@query()
def mesh1_solve(spark, sf_dir):
    """Generation and solution of the full-size system by eight parts, its error, and the slowest part's measured seconds."""
    run = supersteps.run(mesh1_work(spark), *MESH1, f=solve.sine_source, exact=solve.sine_product)
    it, rel = run.end()
    wait = metrics.with_wait(run.costs()).agg(F.max("own").alias("generation_s"), F.sum("wait").alias("wait_s"))
    solving = run.seconds.where("name = 'solve'").agg(F.max("val").alias("solution_s"))
    return run.error().crossJoin(wait).crossJoin(solving).withColumn("iterations", F.lit(it)).withColumn("residual", F.lit(rel))


@query(_forms(GN, LN))
def parts_generation(spark, sf_dir):
    """The same by sixteen parts on meshes that are not aligned, where a local element crosses several global ones."""
    rows = supersteps.work(spark, GN, LN, geometry.crossed_by_overlap(spark, LN, GN), curve_parts(spark, GN, LN, n=16))
    return supersteps.run(rows, GN, LN, solve=False).blocks.groupBy(F.col("name").alias("blk")).agg(F.sum("nnz").alias("nnz"), _r(F.sum("form")).alias("form"))


#: The published numbers of parts and third coefficients; none stands for uniform weights.
PART_COUNTS, THIRD = (8, 16, 32, 64, 128, 256), (None, 20.0, 40.0, 60.0, 80.0)


def full_costs(spark: SparkSession, counts: tuple = PART_COUNTS, true: tuple = (1.0, 1.0, 40.0)) -> tuple[DataFrame, float]:
    """Rows (n_dom, alpha3, k, gg, ll, gl) of the full-size pair by owned rows, for all counts and coefficients; and the price of one part.

    Prices use the coefficients ``true``, so parts cut with the same ones are even by construction: that they win says nothing of
    which coefficient is best on a machine.
    """
    comp = _mesh1_components(spark)
    a, b, c = true
    serial = comp.agg(F.sum(F.col("w_gg") * a + F.col("w_ll") * b + F.col("w_c") * c)).first()[0]
    parts = [curve_parts(spark, *MESH1, None if z is None else weights.combine(comp, (1.0, 1.0, z))).withColumn("alpha3", F.lit(z or 0.0)) for z in THIRD]
    part = reduce(DataFrame.unionByName, parts).withColumn("n_dom", F.explode(F.array(*[F.lit(n) for n in counts])))
    part = part.withColumn("k", F.expr("k div (256 div n_dom)").cast("int"))
    cost = comp.join(part, "v").groupBy("n_dom", "alpha3", "k").agg(F.sum(F.col("w_gg") * a).alias("gg"), F.sum(F.col("w_ll") * b).alias("ll"), F.sum(F.col("w_c") * c).alias("gl"))
    return store(cost, "full-costs"), serial


@query()
def mesh1_scaling(spark, sf_dir):
    """Modelled scaling of the full-size pair: makespan, speedup, efficiency and idle share by part count and coefficient, and the gain by weighting.

    Prices assume a third coefficient of 40 (see ``full_costs``).
    """
    cost, serial = full_costs(spark)
    m = store(metrics.model_summary(cost, serial, "n_dom", "alpha3"), "full-summary")
    plain = m.where("alpha3 = 0").select("n_dom", F.col("makespan").alias("m0"))
    return m.join(F.broadcast(plain), "n_dom").select("n_dom", "alpha3", "makespan", "speedup", (F.col("speedup") / F.col("n_dom") * 100).alias("efficiency"), "idle", (F.col("m0") / F.col("makespan")).alias("gain"))


@query()
def mesh1_breakdown_64(spark, sf_dir):
    """Modelled costs at 64 parts by coefficient: accumulated components, how many parts share the coupling, and how far the global block concentrates."""
    cost, _ = full_costs(spark, (64,))
    w = metrics.with_wait(cost, "alpha3")
    sums = [F.sum(c).alias(c) for c in ("gg", "ll", "gl", "wait")]
    return w.groupBy("alpha3").agg(F.count(F.lit(1)).alias("n_parts"), *sums, F.count_if(F.col("gl") > 0).alias("coupling_parts"), (F.max("gl") / F.sum("gl")).alias("most_coupling"), (F.max("gg") / F.avg("gg")).alias("most_gg"))


@query("SELECT CAST(n AS INT) AS n_dom, 0.006317515::DOUBLE AS error FROM (VALUES (1), (8), (16), (32), (64), (128), (256)) t(n)")
def error_vs_parts(spark, sf_dir):
    """The error with 1 to 256 parts, each of which generates its own rows and takes part in one solution: it must not change, and
    equals that of a direct solution by other code (9 digits, kept as a constant)."""
    fine = curve_parts(spark, G, L)
    counts = (1, *PART_COUNTS)
    part = reduce(DataFrame.unionByName, [fine.select("v", F.expr(f"k div {256 // n}").cast("int").alias("k"), F.lit(n).alias("run")) for n in counts])
    rows = supersteps.work(spark, G, L, geometry.crossed_by_overlap(spark, L, G), part)
    got = [supersteps.run(rows.where(F.col("run") == n).drop("run"), G, L, f=solve.sine_source, exact=solve.sine_product).error() for n in counts]
    return reduce(DataFrame.unionByName, [e.select(F.lit(n).alias("n_dom"), _r("error", 9).alias("error")) for n, e in zip(counts, got, strict=True)])
