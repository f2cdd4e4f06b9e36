"""Methods on Spark: invariants, closed forms and the published behaviour at small size."""

from functools import reduce

import numpy as np
import pytest
from pyspark.sql import functions as F

from overlapgraph.operators import assembly as asm
from overlapgraph.operators import geometry, graph, linalg, meshes, metrics, partition, solve, subdomain, weights
from overlapgraph.operators.meshes import MeshSpec, box_pair
from overlapgraph.plans import catalog_grid, fixtures
from overlapgraph.plans.catalog_grid import error_of, scaling_sweep, system

G, L = box_pair(3, 2, 2, 1 / 3)
GN, LN = box_pair(5, 3, 5, 0.3)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def two_parts(spark, g, local, n=4):
    v = meshes.vertices(spark, g).unionByName(meshes.vertices(spark, local))
    return partition.partition_hash(v, n)


@pytest.mark.parametrize("spec", [G, L, MeshSpec("L", "lagrange", 2, (3, 2), (0.0, 0.0), (1.0, 1.0), 2), MeshSpec("G", "spline", 3, (1, 4), (0.0, 0.0), (1.0, 1.0))])
def test_graph_routes_agree(spark, spec):
    fast = rows(graph.graph_structured(spark, spec).select("i", "j"))
    assert fast == rows(graph.graph_from_incidence(meshes.incidence(spark, spec)).select("i", "j"))
    sup = meshes.supports(spark, spec)
    assert fast == rows(graph.support_graph_bruteforce(sup)) == rows(graph.support_graph(sup, 0.3))


def test_chunked_pairs_equal_plain_pairs(spark):
    inc = spark.createDataFrame([(e, v) for e in range(3) for v in range(e, 40)], "e int, v int")
    assert rows(graph.graph_from_incidence(inc, chunk=7)) == rows(graph.graph_from_incidence(inc, chunk=1000))
    twice = inc.unionAll(inc)
    assert rows(graph.graph_from_incidence(twice)) == rows(graph.graph_from_incidence(inc))


def test_classes_keep_every_link(spark):
    """Classes spelt out give all pairs; two thousand copies give rows by their number, not its square."""
    rng = np.random.default_rng(3)
    rows = {(f"e{int(e)}", int(v)) for e, v in zip(rng.integers(0, 12, 300), rng.integers(0, 120, 300), strict=True)} | {("one", 900), ("lone", 901), (None, 902)}
    rows |= {("copy", 1000 + k) for k in range(2000)} | {("copy", 5), ("other", 1000), ("other", 5)}
    inc = spark.createDataFrame(sorted(rows, key=str), "e string, v long").where("e is not null")
    got = graph.graph_of_classes(inc).collect()
    assert len(got) < 2 * len(rows)
    members: dict = {}
    for r in got:
        if r.kind == "member":
            members.setdefault(r.i, []).append(r.j)
    assert {i: min(m) for i, m in members.items()} == {i: i for i in members} and sum(map(len, members.values())) == len({v for m in members.values() for v in m})
    pairs = {(a, b) for m in members.values() for a in m for b in m if a < b}
    pairs |= {(min(a, b), max(a, b)) for r in got if r.kind == "link" for a in members[r.i] for b in members[r.j]}
    assert pairs == {(r.i, r.j) for r in graph.graph_from_incidence(inc).where("i <> j").collect()}


def test_between_meshes_exact_and_sampled(spark):
    cells = geometry.crossed_elements(geometry.coupling_map(geometry.quadrature(spark, LN, 4), GN))
    sampled = set(rows(graph.graph_from_cells(cells, meshes.incidence(spark, LN), meshes.incidence(spark, GN)).select("i", "j")))
    exact = set(rows(graph.graph_between(spark, LN, GN).select("i", "j")))
    assert sampled <= exact
    assert sampled == exact  # every overlap holds an integration point here
    assert rows(cells.select("e_l", "e_g")) == rows(geometry.crossed_by_overlap(spark, LN, GN))


def test_golden_counts(spark):
    for n, p, m, side, gg, ll, gl in ((5, 3, 4, 0.2, 85_184, 2_197, 8_000), (5, 1, 4, 0.4, 4_096, 2_197, 1_331), (5, 2, 4, 0.4, 24_389, 2_197, 4_096)):
        g, local = box_pair(n, p, m, side)
        got = {r.kind: (r.nnz, r.n_edges) for r in graph.graph_stats(graph.graph_overlay(spark, g, local)).collect()}
        assert got["GG"][0] == gg and got["LL"][0] == ll and got["GL"][1] == gl


def test_weights_are_conserved_for_irregular_elements(spark, sf):
    parts = fixtures.orders_parts(spark, sf), fixtures.customers_suppliers(spark, sf), fixtures.customer_orders(spark, sf)
    r = weights.weight_audit(weights.weight_components(*parts, 8), *parts, 8).first()
    assert r.v_gg == pytest.approx(r.e_gg) and r.v_ll == pytest.approx(r.e_ll) and r.v_c == pytest.approx(r.e_c)


def test_partition_covers_and_halo_is_disjoint(spark):
    e, p = graph.graph_overlay(spark, G, L), two_parts(spark, G, L)
    assert p.count() == G.n_vertices + L.n_vertices == p.select("v").distinct().count()
    h = subdomain.halo(e, p)
    assert h.join(p, ["v", "k"]).count() == 0
    both = {(r.i, r.j) for r in graph.symmetric(e).collect()}
    k = {r.v: r.k for r in p.collect()}
    want = {(k[i], j, k[j]) for i, j in both if k[i] != k[j]}
    assert {(r.k, r.v, r.owner) for r in h.collect()} == want


def test_owned_assembly_equals_whole(spark):
    e, p = graph.graph_overlay(spark, G, L), two_parts(spark, G, L)
    ext, inc = subdomain.extended_sets(e, p), meshes.incidence(spark, G)
    whole = {(r.i, r.j): r.val for r in asm.k_own(spark, G).collect()}
    for rule in ("containment", "owner"):
        got = asm.assemble_owned(subdomain.assign_elements(inc, ext, rule), asm.own_block(G, 4, "laplace"), p, 4).collect()
        assert len(got) == len(whole) and all(r.val == pytest.approx(whole[r.i, r.j], abs=1e-12) for r in got)


def test_owned_coupling_equals_whole(spark):
    e, p = graph.graph_overlay(spark, GN, LN), two_parts(spark, GN, LN, 3)
    ext = subdomain.extended_sets(e, p)
    inc_l, inc_g = meshes.incidence(spark, LN), meshes.incidence(spark, GN)
    cells = subdomain.assign_cells(geometry.crossed_by_overlap(spark, LN, GN), inc_l, inc_g, ext)
    got = {(r.i, r.j): r.val for r in asm.assemble_owned(cells, asm.coupling_block(LN, GN, 4, "laplace"), p, 3).collect()}
    want = {(r.i, r.j): r.val for r in asm.k_coupling(spark, LN, GN).collect()}
    assert got.keys() == want.keys() and all(got[z] == pytest.approx(want[z], abs=1e-12) for z in want)


def test_matrix_invariants(spark):
    k = asm.block_system(asm.k_own(spark, G), asm.k_coupling(spark, L, G), asm.k_own(spark, L))
    val = {(r.i, r.j): r.val for r in k.collect()}
    assert all(abs(v - val[j, i]) < 1e-12 for (i, j), v in val.items())
    for blk in ("GG", "LL", "GL"):
        worst = k.where(F.col("blk") == blk).groupBy("j").agg(F.abs(F.sum("val")).alias("s")).agg(F.max("s")).first()[0]
        assert worst < 1e-10
    pattern = set(rows(graph.candidate_pattern(graph.graph_overlay(spark, G, L))))
    assert set(val) <= pattern
    assert asm.on_pattern(k.select("i", "j", "val"), graph.candidate_pattern(graph.graph_overlay(spark, G, L))).count() == len(pattern)
    packed = asm.to_rows(k.select("i", "j", "val"))
    assert rows(asm.to_entries(packed)) == sorted((i, j, v) for (i, j), v in val.items())


def test_products_agree(spark):
    e, p = graph.graph_structured(spark, G), partition.partition_hash(meshes.vertices(spark, G), 3)
    k = asm.k_structured(spark, G)
    x = meshes.vertices(spark, G).select("v", (F.col("v") % 7).cast("double").alias("x"))
    comm = subdomain.comm_plan(subdomain.halo(e, p))
    a = {r.v: r.x for r in linalg.spmv_parts(linalg.owned_rows(k, p), x, p, comm).collect()}
    b = {r.v: r.x for r in linalg.spmv(k, x).collect()}
    assert a.keys() == b.keys() and all(a[v] == pytest.approx(b[v], abs=1e-10) for v in b)
    assert sum(r.dot for r in linalg.dot_parts(x, x, p).collect()) == pytest.approx(linalg.dot(x, x)) == pytest.approx(linalg.norm2(x) ** 2)
    split = linalg.split_blocks(linalg.owned_rows(k, p), p)
    assert split.count() == k.count() and split.where("inner").count() < k.count()


def test_small_solvers_agree(spark):
    k, f = system(spark, G, L)
    k, f = k.cache(), f.cache()
    dense = {r.v: r.x for r in solve.solve_local(spark, k, f, method="dense").x.collect()}
    for m in ("bicgstab", "cg"):
        s = solve.solve_local(spark, k, f, method=m)
        assert s.residual < 1e-8 and s.iterations <= len(dense)
        assert all(r.x == pytest.approx(dense[r.v], abs=1e-6) for r in s.x.collect())
    ident = asm.apply_dirichlet(
        asm.block_system(asm.k_own(spark, G), asm.k_coupling(spark, L, G), asm.k_own(spark, L)).select("i", "j", "val"),
        asm.rhs(spark, G, solve.sine_source).unionByName(asm.rhs(spark, L, solve.sine_source)),
        meshes.vertices(spark, G).unionByName(meshes.vertices(spark, L)).where("fixed").select("v", F.lit(0.0).alias("value")), "identity",
    )
    full = {r.v: r.x for r in solve.solve_local(spark, *ident, method="dense").x.collect()}
    assert all(full[v] == pytest.approx(x, abs=1e-9) for v, x in dense.items())


def test_distributed_solver_on_a_line(spark):
    g = MeshSpec("G", "spline", 2, (6,), (0.0,), (1.0,))
    k = asm.k_own(spark, g)
    f = asm.rhs(spark, g, solve.sine_source)
    fixed = meshes.vertices(spark, g).where("fixed").select("v", F.lit(0.0).alias("value"))
    k, f = asm.apply_dirichlet(k, f, fixed)
    p = partition.partition_hash(f.select("v"), 2)
    comm = subdomain.comm_plan(subdomain.halo(k.where("i <= j"), p))
    s = solve.bicgstab(linalg.owned_rows(k, p), f, p, comm, tol=1e-9)
    want = {r.v: r.x for r in solve.solve_local(spark, k, f, method="dense").x.collect()}
    assert s.residual <= 1e-9 and all(r.x == pytest.approx(want[r.v], abs=1e-7) for r in s.x.collect())


def test_distributed_solver_on_the_overlay(spark, sf, monkeypatch):
    seen = []
    whole = solve.bicgstab
    monkeypatch.setattr(solve, "bicgstab", lambda kp, f, part, comm, **kw: seen.append((part.select("k").distinct().count(), comm.count())) or whole(kp, f, part, comm, **kw))
    got = {r.method: r for r in catalog_grid.QUERIES["solve_mms_parts"](spark, sf).collect()}
    pair = catalog_grid.GS, catalog_grid.LS
    want = error_of(spark, *pair, solve.solve_local(spark, *system(spark, *pair), method="dense").x).first()["error"]
    assert sorted(got) == ["bicgstab", "cg", "jacobi"] and got["bicgstab"].engine == "parts"
    assert len(seen) == 1 and seen[0][0] == 4 and seen[0][1] > 0
    assert all(r.residual < 1e-8 and r.error == pytest.approx(want, rel=1e-6) for r in got.values())


@pytest.mark.parametrize("args,error,eps_g,eps_l", [((5, 3, 4, 0.4), 6.317515e-3, 4.928664e-6, 6.021058e-8), ((5, 2, 4, 0.4), 2.807269e-2, 9.442466e-5, 4.084866e-6)])
def test_golden_errors(spark, args, error, eps_g, eps_l):
    g, local = box_pair(*args)
    k, f = system(spark, g, local)
    r = error_of(spark, g, local, solve.solve_local(spark, k, f).x).first()
    assert r.error == pytest.approx(error, rel=1e-5) and r.eps_g == pytest.approx(eps_g, rel=1e-4) and r.eps_l == pytest.approx(eps_l, rel=1e-4)


def test_shared_layers_follow_the_degree(spark):
    got = {r.p: (r.shared, r.layers) for r in catalog_grid.shared_layers(spark, "").collect()}
    assert got == {p: (20**3 - (20 - p) ** 3, p) for p in (1, 2, 3)}


def test_weighting_behaves_as_published(spark):
    """Weights with the true coefficient win; smaller and larger ones pay on either side; idle time falls and rises."""
    r = {x.alpha3: x for x in scaling_sweep(spark, *box_pair(10, 3, 10, 0.2), parts=(8,), third=(None, 20.0, 40.0, 80.0)).collect()}
    assert r[40.0].speedup > r[20.0].speedup > r[0.0].speedup and r[40.0].speedup > r[80.0].speedup
    assert r[40.0].idle < r[20.0].idle < r[0.0].idle and r[80.0].idle > r[40.0].idle


def test_rcb_and_curves_balance(spark):
    v = meshes.vertices(spark, GN).unionByName(meshes.vertices(spark, LN))
    w = weights.combine(weights.weight_components(meshes.incidence(spark, GN), meshes.incidence(spark, LN), geometry.crossed_by_overlap(spark, LN, GN), 64), (1.0, 1.0, 40.0))
    parts = [partition.partition_rcb(v, w, 5), *[partition.partition_curve(v, w, 5, [0.0] * 3, [1.0] * 3, c) for c in ("morton", "hilbert")]]
    for p in parts:
        b = partition.balance(w, p, 5)
        assert b.count() == 5 and b.agg(F.max("share")).first()[0] < 1.15 and p.count() == v.count()


def test_error_does_not_depend_on_the_parts(spark, sf):
    got = {r.n_dom: r.error for r in catalog_grid.QUERIES["error_vs_parts"](spark, sf).collect()}
    assert sorted(got) == [1, 8, 16, 32, 64, 128, 256]
    assert all(x == pytest.approx(6.317515e-3, rel=1e-6) for x in got.values())


def test_products_move_only_the_vector(spark):
    from overlapgraph.plans import planner

    e, p = graph.graph_structured(spark, G), partition.partition_hash(meshes.vertices(spark, G), 3)
    x = meshes.vertices(spark, G).select("v", (F.col("v") % 7).cast("double").alias("x"))
    comm = subdomain.comm_plan(subdomain.halo(e, p))
    kp = linalg.place_parts(linalg.owned_rows(asm.k_structured(spark, G), p), 3)
    kp.count()
    plan = linalg.spmv_parts(kp, x, p, comm)._jdf.queryExecution().executedPlan().toString()
    side = plan.split("FlatMapCoGroups")[1]
    # the cached matrix is read below the product without an exchange or a sort of its own
    at = side.index("InMemoryTableScan")
    assert "Exchange" not in side[:at] and "Sort" not in side[:at], side
    kp.unpersist()
    assert "Exchange" in planner.plan_text(linalg.spmv(asm.k_structured(spark, G), x))


def test_batches_of_element_matrices(spark):
    for spec in (G, L, MeshSpec("L", "lagrange", 2, (3, 2), (0.0, 0.0), (1.0, 1.0), 2)):
        whole = {(r.i, r.j): r.val for r in asm.k_own(spark, spec, form="laplace+mass").collect()}
        ids = np.arange(spec.n_vertices) + spec.offset
        assert sum(whole.values()) == pytest.approx(float(np.prod([b - a for a, b in zip(spec.lo, spec.hi)])))  # a field of ones: no slope, mass one
        assert {i for i, _ in whole} == set(ids.tolist())


def test_multilevel_beats_scattering(spark, sf):
    turns = spark.range(400).select(F.col("id").alias("v"))
    e = turns.select(F.col("v").alias("i"), F.explode(F.array(F.col("v"), F.col("v") + 1, F.col("v") + 2)).alias("j")).where("j < 400")
    w = weights.uniform_weights(turns)
    p = partition.partition_multilevel(e, w, 4, coarse=60)
    cut, scattered = (partition.cut_size(e, q).first().cut for q in (p, partition.partition_hash(turns, 4)))
    assert cut < scattered / 4 and partition.balance(w, p, 4).agg(F.max("share")).first()[0] <= 1.03 + 1e-9
    assert p.count() == 400


def test_multilevel_takes_few_rounds(spark, monkeypatch):
    """Each round reads all edges, so their number must not follow the halving of the vertices."""
    rng = np.random.default_rng(5)
    ends = np.unique(np.sort(rng.integers(0, 3000, (30_000, 2)), 1), axis=0)
    e = spark.createDataFrame([(int(a), int(b)) for a, b in ends if a < b], "i long, j long")
    w = spark.range(3000).select(F.col("id").alias("v"), (1.0 + F.col("id") % 3).alias("w"))
    rounds, real = [], partition.store
    monkeypatch.setattr(partition, "store", lambda df, name: (rounds.append(name), real(df, name))[1])
    part = partition.partition_multilevel(e, w, 4, coarse=60)
    assert rounds.count("ml-map") <= 6
    assert part.count() == 3000 and partition.balance(w, part, 4).where("share > 1.03 + 1e-9").isEmpty()
    hashed = partition.partition_hash(w, 4)
    both = partition.cut_sizes(e, {"a": part, "b": hashed}).first()
    assert both["a"] == partition.cut_size(e, part).first()["cut"] < both["b"] == partition.cut_size(e, hashed).first()["cut"]


def test_multilevel_reaches_the_driver_size_on_stars(spark, monkeypatch):
    seen, grow = [], partition._grow
    monkeypatch.setattr(partition, "_grow", lambda n, *a: seen.append(n) or grow(n, *a))
    leaves = [(s, 8 + s * 300 + i) for s in range(8) for i in range(300)]
    e = spark.createDataFrame(leaves + [(s, s + 1) for s in range(7)], "i long, j long")
    w = spark.createDataFrame([(v, 400.0 if v < 8 else 1.0) for v in range(2408)], "v long, w double")
    part = partition.partition_multilevel(e, w, 4, coarse=100)
    assert len(seen) == 1 and seen[0] <= 100 and part.count() == 2408
    assert partition.cut_size(e, part).first()["cut"] < 0.5 * len(leaves)


def test_per_mesh_partition_misses_edges(spark):
    e, p = graph.graph_overlay(spark, G, L), two_parts(spark, G, L)
    seen = partition.cut_size(graph.graph_without_coupling(e), p).first().cut
    assert seen < partition.cut_size(e, p).first().cut


def test_two_mesh_fit_is_not_worse(spark, sf):
    from overlapgraph.plans.catalog_data import fit_events

    one, two = (fit_events(spark, sf, b)[1].first() for b in (False, True))
    assert one.sse == pytest.approx(2_216_777.839, rel=1e-6) and two.sse == pytest.approx(2_163_861.083, rel=1e-6)


def test_empty_inputs(spark):
    none = spark.createDataFrame([], "e long, v long")
    assert graph.graph_from_incidence(none).count() == 0
    p = spark.createDataFrame([], "v long, k int")
    e = spark.createDataFrame([], "i long, j long, kind string")
    assert subdomain.extended_sets(e, p).count() == 0 and subdomain.assign_elements(none, subdomain.extended_sets(e, p)).count() == 0
    pts = spark.createDataFrame([], "x array<double>, w double")
    assert asm.gram_entries(pts, fixtures.time_pair()[0]).count() == 0


def test_points_on_faces_go_up(spark):
    g = MeshSpec("G", "spline", 1, (5,), (0.0,), (1.0,))
    pts = spark.createDataFrame([([x],) for x in (0.0, 0.2, 0.2 - 1e-10, 0.2 - 1e-6, 0.6, 1.0)], "x array<double>")
    want = [0, 1, 1, 0, 3, 4]
    assert [r.e_g for r in geometry.locate_bucket(pts, g).collect()] == want
    assert [r.e_g for r in geometry.locate_tree(pts, g).collect()] == want
    assert sorted(r.e_g for r in geometry.locate_range(pts, geometry.boxes(spark, g), g, 3).collect()) == sorted(want)


def test_blocks_of_three(spark):
    k = spark.createDataFrame([(0, 1, [float(z) for z in range(9)]), (1, 1, [1.0, 0.0, 0.0, 0.0, 1.0, 0.0, 0.0, 0.0, 1.0])], "i long, j long, val array<double>")
    x = spark.createDataFrame([(1, [1.0, 2.0, 3.0])], "v long, x array<double>")
    got = {r.v: r.x for r in linalg.spmv(k, x, 3).collect()}
    assert got == {0: list(np.arange(9).reshape(3, 3) @ np.array([1, 2, 3])), 1: [1.0, 2.0, 3.0]}
    s = linalg.lincomb(2.0, x, -1.0, x).first().x
    assert s == [1.0, 2.0, 3.0] and linalg.dot(x, x) == 14.0


def test_model_identities(spark):
    c = spark.createDataFrame([(0, 4.0, 1.0, 2.0), (1, 1.0, 1.0, 1.0), (2, 0.0, 0.0, 9.0)], "k int, gg double, ll double, gl double")
    w = metrics.with_wait(c).collect()
    assert min(r.wait for r in w) == 0 and all(r.own + r.wait == 9.0 for r in w)
    s = metrics.model_summary(c, 19.0).first()
    assert s.makespan == 9.0 and s.speedup == pytest.approx(19 / 9) and s.idle == pytest.approx(8 / 27)
    assert reduce(lambda a, b: a + b, [r.share for r in metrics.breakdown(c).collect()]) == pytest.approx(3.0)


def test_stores(spark, tmp_path):
    from overlapgraph.sources import tables

    k = asm.k_own(spark, MeshSpec("G", "spline", 2, (4,), (0.0,), (1.0,)))
    for form in ("csv", "json", "orc", "parquet"):
        tables.write_coo(k, f"{tmp_path}/{form}", form)
        assert rows(tables.read_coo(spark, f"{tmp_path}/{form}", form)) == rows(k)
    db = geometry.geometric_database(spark, L, 2)
    tables.save_geometry(db, f"{tmp_path}/geo", "L")
    assert tables.load_geometry(spark, f"{tmp_path}/geo", "L").count() == db.count() == L.n_elements * 8
    p = partition.partition_hash(meshes.vertices(spark, G), 3)
    tables.save_parts(p, f"{tmp_path}/parts")
    assert tables.load_part(spark, f"{tmp_path}/parts", 1).count() == p.where("k = 1").count()
