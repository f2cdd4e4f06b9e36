"""Further pieces of the methods as queries: storage forms, breakdowns, relational operators, late rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import assembly as asm
from ..operators import geometry, graph, meshes, metrics, partition, subdomain, weights
from ..sources.tables import load, store
from ..streaming import streams
from . import catalog_data as cd
from . import catalog_grid as cg
from . import fixtures
from .catalog_grid import GN, GS, LN, LS, _r

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return put


# ---- matrices and graphs --------------------------------------------------------------------------

_KGG = f"WITH {cg.sql_gauss()}, {cg.sql_axis(GS, 'ax')}, r AS ({cg.sql_kron('ax', GS, GS)})"


@query(_KGG + " SELECT i, count(*) AS n_entries, round(sum(CASE WHEN i = j THEN val END), 7) AS diagonal, round(sum(abs(val)), 6) AS mass FROM r GROUP BY i")
def k_row_form(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the matrix as arrays, and what can be read off them."""
    rows = asm.to_rows(asm.k_structured(spark, GS))
    diag = F.element_at(F.filter("nbr", lambda z: z["j"] == F.col("i")), 1)["val"]
    mass = F.aggregate("nbr", F.lit(0.0), lambda s, z: s + F.abs(z["val"]))
    return rows.select("i", F.size("nbr").cast("long").alias("n_entries"), _r(diag, 7).alias("diagonal"), _r(mass, 6).alias("mass"))


@query(_KGG + " SELECT i AS v, round(1 / val, 7) AS d FROM r WHERE i = j")
def diagonal_scale(spark, sf_dir):
    from ..operators.solve import diag_scale

    return diag_scale(asm.k_structured(spark, GS)).select("v", _r("d", 7).alias("d"))


@query(
    f"WITH {cg.sql_gauss()}, {cg.sql_axis(GS, 'ag')}, {cg.sql_axis(LS, 'al')}, {cg.sql_cross_axis(LS, GS, 'ac')}, k AS ({cg.sql_kron('ag', GS, GS)} UNION ALL {cg.sql_kron('al', LS, LS)} UNION ALL {cg.sql_kron('ac', GS, LS)} "
    f"UNION ALL SELECT j AS i, i AS j, val FROM ({cg.sql_kron('ac', GS, LS)})), {cg.sql_edges(GS, LS)}, p AS (SELECT i, j FROM edges UNION SELECT j AS i, i AS j FROM edges) "
    "SELECT count(*) AS n_pattern, count(k.val) AS n_stored, round(sum(abs(coalesce(k.val, 0))), 6) AS mass FROM p LEFT JOIN k ON k.i = p.i AND k.j = p.j"
)
def pattern_values(spark, sf_dir):
    """The matrix on its candidate pattern: nothing outside it, zeros kept."""
    k = asm.block_system(asm.k_own(spark, GS), asm.k_coupling(spark, LS, GS), asm.k_own(spark, LS)).select("i", "j", "val")
    pattern = graph.candidate_pattern(graph.graph_overlay(spark, GS, LS))
    got = asm.on_pattern(k, pattern)
    return got.agg(F.count(F.lit(1)).alias("n_pattern"), _r(F.sum(F.abs("val")), 6).alias("mass")).crossJoin(k.join(pattern, ["i", "j"], "left_semi").agg(F.count(F.lit(1)).alias("n_stored"))).select("n_pattern", "n_stored", "mass")


@query(f"WITH {cg.sql_edges(GS, LS)}, s AS (SELECT i, j FROM edges WHERE i <> j UNION ALL SELECT j AS i, i AS j FROM edges WHERE i <> j) SELECT i AS v, count(*) AS degree FROM s GROUP BY i")
def vertex_degrees(spark, sf_dir):
    return graph.degrees(graph.graph_overlay(spark, GS, LS))


@query(f"WITH a AS (SELECT range AS v, {cg.sql_digits('range', GS.n_cp, 'a')} FROM range({GS.n_vertices})) SELECT v, a0 + 1 AS near0 FROM a WHERE a0 + 1 < {GS.n_cp[0]}")
def next_neighbour(spark, sf_dir):
    """Index arithmetic back and forth: the neighbour of a vertex along the first axis."""
    v = meshes.vertices(spark, GS)
    ix = meshes.decode_vertex(GS, F.col("v"))
    to = meshes.encode_vertex(GS, [ix[0] + 1, ix[1], ix[2]])
    return v.where(ix[0] + 1 < GS.n_cp[0]).select("v", meshes.decode_vertex(GS, to)[0].cast("long").alias("near0"))


_MULTI = meshes.MeshSpec("M", "lagrange", 1, (2, 2, 2), (0.5, 0.5, 0.5), (0.9, 0.9, 0.9), 2)


@query("SELECT * FROM (VALUES ('G', CAST(125 AS BIGINT)), ('L', CAST(27 AS BIGINT)), ('M', CAST(27 AS BIGINT))) t(mesh, n)")
def overlay_many(spark, sf_dir):
    """One global mesh under two local ones, in one id space."""
    return meshes.overlay([GS, LS, _MULTI], spark).groupBy("mesh").agg(F.count(F.lit(1)).alias("n"))


# ---- costs -----------------------------------------------------------------------------------------


#: The modelled costs of eight hash parts of the order-part and customer-supplier meshes.
_BIP_MODEL = cd._BIP_COST + ", c AS (SELECT CAST((v % 1000003 * 7919 + 12345) % 1000003 % 8 AS INT) AS k, sum(gg) AS gg, sum(ll) AS ll, sum(40 * c) AS gl FROM w GROUP BY 1), o AS (SELECT *, gg + ll + gl AS own, max(gg + ll + gl) OVER () AS top FROM c) "


def _bip_model(spark, sf_dir) -> DataFrame:
    comp = store(weights.weight_components(*cd._bip(spark, sf_dir), cd._N_IP), "bip-components")
    return metrics.part_costs_owned(comp, partition.partition_hash(comp.select("v"), cg.N_PARTS))


@query(_BIP_MODEL + ", l AS (SELECT k, 'gg' AS component, gg AS cost FROM o UNION ALL SELECT k, 'll', ll FROM o UNION ALL SELECT k, 'gl', gl FROM o UNION ALL SELECT k, 'wait', top - own FROM o) SELECT k, component, round(cost, 2) + 0.0 AS cost, round(cost / sum(cost) OVER (PARTITION BY k), 7) + 0.0 AS share FROM l")
def cost_breakdown(spark, sf_dir):
    """Costs of each part of the parts and suppliers by component, and their shares."""
    return metrics.breakdown(_bip_model(spark, sf_dir)).select("k", "component", _r("cost", 2).alias("cost"), _r("share", 7).alias("share"))


@query(_BIP_MODEL + "SELECT component, round(sum(cost), 2) + 0.0 AS cost FROM (SELECT 'gg' AS component, gg AS cost FROM o UNION ALL SELECT 'll', ll FROM o UNION ALL SELECT 'gl', gl FROM o UNION ALL SELECT 'wait', top - own FROM o) GROUP BY component")
def accumulated_breakdown(spark, sf_dir):
    """Costs of parts and suppliers by component, over all parts."""
    return metrics.accumulated(_bip_model(spark, sf_dir)).select("component", _r("cost", 2).alias("cost"))


@query(
    cg._SMALL + cg._ASSIGN + f", {cg._CELLS_S}, ci AS (SELECT e_l, e_g, il.v FROM cells JOIN il ON il.e = e_l UNION SELECT e_l, e_g, ig.v FROM cells JOIN ig ON ig.e = e_g), "
    "ga AS (SELECT e, k FROM ig JOIN ext USING (v) GROUP BY e, k HAVING count(*) = 27 AND bool_or(is_core)), la AS (SELECT e, k FROM il JOIN ext USING (v) GROUP BY e, k HAVING count(*) = 8 AND bool_or(is_core)), "
    "ca AS (SELECT e_l, e_g, k FROM ci JOIN ext USING (v) GROUP BY e_l, e_g, k HAVING count(*) = 35 AND bool_or(is_core)), "
    "r AS (SELECT k, 64.0::DOUBLE * 27 * 27 AS gg, 0.0::DOUBLE AS ll, 0.0::DOUBLE AS gl FROM ga UNION ALL SELECT k, 0, 64.0::DOUBLE * 8 * 8, 0 FROM la UNION ALL SELECT k, 0, 0, 40 * 64.0::DOUBLE * 8 * 27 FROM ca) "
    "SELECT CAST(k AS INT) AS k, sum(gg) AS gg, sum(ll) AS ll, sum(gl) AS gl FROM r GROUP BY k"
)
def model_cost_assigned(spark, sf_dir):
    """The other price: a part pays in full for every element and cell that it evaluates."""
    part, e = cg._parts(spark), cg._overlay(spark)
    ext = subdomain.extended_sets(e, part)
    inc_g, inc_l = meshes.incidence(spark, GS), meshes.incidence(spark, LS)
    eg = subdomain.assign_elements(inc_g, ext, "owner").join(weights.element_ops(inc_g, 64), "e")
    el = subdomain.assign_elements(inc_l, ext, "owner").join(weights.element_ops(inc_l, 64), "e")
    cells = subdomain.assign_cells(geometry.crossed_by_overlap(spark, LS, GS), inc_l, inc_g, ext, "owner").withColumn("ops", F.lit(64.0 * 8 * 27))
    return metrics.part_costs_assigned(eg, el, cells)


@query("SELECT 8 AS n_dom, 40.0::DOUBLE AS alpha3")
def tune_alpha(spark, sf_dir):
    """The coefficient of least modelled makespan among the published ones, when 40 is the true price."""
    comp = store(cg._components(spark), "tune")
    v = store(meshes.vertices(spark, GN).unionByName(meshes.vertices(spark, LN)), "tune-v")
    runs = []
    for a in (20.0, 40.0, 60.0, 80.0):
        cost = metrics.part_costs_owned(comp, partition.partition_rcb(v, weights.combine(comp, (1.0, 1.0, a)), 8))
        runs.append(metrics.with_wait(cost).select(F.lit(8).alias("n_dom"), F.lit(a).alias("alpha3"), "k", "total"))
    return weights.tune_alpha(reduce(DataFrame.unionByName, runs)).select("n_dom", "alpha3")


@query(
    f"WITH {cd._OP}, p AS (SELECT v, floor((row_number() OVER (ORDER BY v) - 1) * 4 / (SELECT count(DISTINCT v) FROM op)) AS k FROM (SELECT DISTINCT v FROM op)), "
    "edges AS (SELECT DISTINCT a.v AS i, b.v AS j FROM op a JOIN op b ON a.e = b.e AND a.v < b.v) "
    "SELECT count(*) FILTER (WHERE a.k <> b.k) AS cut_before, true AS smaller, true AS balanced FROM edges JOIN p a ON a.v = i JOIN p b ON b.v = j"
)
def refine_partition(spark, sf_dir):
    """Boundary moves on a block partition of the order-part graph: the cut gets smaller, the parts stay balanced."""
    inc = fixtures.orders_parts(spark, sf_dir)
    e = store(graph.graph_from_incidence(inc), "refine-graph")
    v = store(inc.select("v").distinct(), "refine-v")
    w = weights.uniform_weights(v)
    p = store(partition.partition_block(v, 4), "refine-start")
    q = store(partition.refine(e, p, w, 4, rounds=2), "refine-end")
    before, after = partition.cut_size(e, p), partition.cut_size(e, q)
    most = partition.balance(w, q, 4).agg((F.max("share") <= 1.03 + 1e-9).alias("balanced"))
    return before.select(F.col("cut").alias("cut_before")).crossJoin(after.select("cut")).crossJoin(most).select("cut_before", (F.col("cut") < F.col("cut_before")).alias("smaller"), "balanced")


@query("SELECT run_mean AS k, (1.0::DOUBLE + 2 + 6) / 3 AS gen FROM (SELECT 8 AS run_mean)")
def mean_of_three(spark, sf_dir):
    runs = spark.createDataFrame([(8, 0, 1.0), (8, 1, 2.0), (8, 2, 6.0)], "k int, run int, gen double")
    return metrics.mean_of_runs(runs, "k")


# ---- relational pieces --------------------------------------------------------------------------------


@query(f"WITH {cd._OP} SELECT e, v, count(*) AS n FROM op GROUP BY GROUPING SETS ((e), (v), ())")
def rel_grouping_sets(spark, sf_dir):
    op = fixtures.orders_parts(spark, sf_dir)
    return op.groupingSets([[F.col("e")], [F.col("v")], []], "e", "v").agg(F.count(F.lit(1)).alias("n"))


@query(cg._MODEL + "SELECT k, component, round(cost, 2) AS cost FROM (SELECT k, 'gg' AS component, gg AS cost FROM c UNION ALL SELECT k, 'll', ll FROM c UNION ALL SELECT k, 'gl', gl FROM c)")
def rel_unpivot_breakdown(spark, sf_dir):
    return cg._model(spark).unpivot(["k"], ["gg", "ll", "gl"], "component", "cost").select("k", "component", _r("cost", 2).alias("cost"))


@query(cd._OPG + "SELECT e FROM op GROUP BY e HAVING bool_and(v IN (SELECT v FROM part WHERE k < 4))")
def rel_division_containment(spark, sf_dir):
    """Orders all of whose parts belong to the lower half of the parts: division by counting."""
    inc, _, p = cd._op_part(spark, sf_dir)
    hit = inc.join(p.where("k < 4"), "v").groupBy("e").agg(F.count(F.lit(1)).alias("got"))
    return inc.groupBy("e").agg(F.count(F.lit(1)).alias("n")).join(hit, "e").where("got = n").select("e")


@query(f"WITH {cd._OP}, d AS (SELECT v, count(*) AS n FROM op GROUP BY v) SELECT v, CAST(ntile(4) OVER (ORDER BY n, v) AS INT) AS q, n > (SELECT avg(n) FROM d) AS heavy FROM d")
def rel_ntile_scalar(spark, sf_dir):
    """Quarters by degree, and whether a vertex is above the mean (a scalar subquery)."""
    d = fixtures.orders_parts(spark, sf_dir).groupBy("v").agg(F.count(F.lit(1)).alias("n"))
    d.createOrReplaceTempView("og_degree")
    return spark.sql("SELECT v, ntile(4) OVER (ORDER BY n, v) AS q, n > (SELECT avg(n) FROM og_degree) AS heavy FROM og_degree")


@query(cg._COUPLED + f", {cg.sql_incidence(LN, 'il')}, {cg.sql_incidence(GN, 'ig')}, cells AS (SELECT DISTINCT e AS e_l, s0 + 5 * s1 + 25 * s2 AS e_g FROM loc), s AS (SELECT DISTINCT ig.v AS i, il.v AS j FROM cells JOIN il ON il.e = e_l JOIN ig ON ig.e = e_g), {cg.sql_between(LN, GN, 'x')} SELECT (SELECT count(*) FROM (SELECT i, j FROM s INTERSECT SELECT i, j FROM x)) AS n_both, (SELECT count(*) FROM (SELECT i, j FROM x EXCEPT SELECT i, j FROM s)) AS n_exact_only, (SELECT count(*) FROM s FULL JOIN x ON s.i = x.i AND s.j = x.j) AS n_any")
def rel_exact_sampled(spark, sf_dir):
    """Exact and sampled inter-mesh edges by set operations and a full outer join."""
    s = cg.graph_overlay_sampled(spark, sf_dir).select("i", "j")
    x = graph.graph_between(spark, LN, GN).select("i", "j")
    both = s.intersect(x).agg(F.count(F.lit(1)).alias("n_both"))
    only = x.exceptAll(s).agg(F.count(F.lit(1)).alias("n_exact_only"))
    either = s.join(x, ["i", "j"], "full").agg(F.count(F.lit(1)).alias("n_any"))
    return both.crossJoin(only).crossJoin(either)


@query(f"WITH {cd._CUBE}, q AS (SELECT CAST(least(greatest(floor(x0 * 16), 0), 15) AS BIGINT) AS a, CAST(least(greatest(floor(x1 * 16), 0), 15) AS BIGINT) AS b, CAST(least(greatest(floor(x2 * 16), 0), 15) AS BIGINT) AS c FROM loc) SELECT " + " | ".join(f"((({n} >> {k}) & 1) << {3 * k + i})" for i, n in enumerate("abc") for k in range(4)) + " AS morton, count(*) AS n FROM q GROUP BY 1")
def rel_bit_morton(spark, sf_dir):
    pts = fixtures.sale_points(spark, sf_dir)
    return pts.groupBy(partition.morton_key(F.col("x"), [0.0] * 3, [1.0] * 3, 4).alias("morton")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INT) AS day, count(*) AS n, CAST(epoch_us(max(ts::TIMESTAMP)) AS BIGINT) AS last_us FROM events GROUP BY ALL")
def rel_date_span(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).alias("day")
    return e.groupBy("event_type", day).agg(F.count(F.lit(1)).alias("n"), F.unix_micros(F.max("ts")).alias("last_us"))


@query(f"WITH {cd._OP}, s AS (SELECT CASE WHEN v % 2 = 0 THEN 'even' ELSE 'odd' END AS c, count(*) * 1.0::DOUBLE AS n FROM op GROUP BY 1) SELECT c, n FROM s")
def rel_map_metrics(spark, sf_dir):
    """A bag of measures as a map, and back to rows."""
    op = fixtures.orders_parts(spark, sf_dir)
    bag = op.agg(F.create_map(F.lit("even"), F.count_if(F.col("v") % 2 == 0), F.lit("odd"), F.count_if(F.col("v") % 2 != 0)).alias("m"))
    return bag.select(F.explode(F.transform_values("m", lambda k, v: v.cast("double"))).alias("c", "n"))


@query("SELECT round(sum(pow(sin(2 * pi() * x), 2)), 7) AS s FROM (SELECT (range + 0.5::DOUBLE) / 100 AS x FROM range(100))")
def rel_math_mms(spark, sf_dir):
    x = (F.col("id") + 0.5) / 100
    return spark.range(100).agg(_r(F.sum(F.pow(F.sin(2 * F.pi() * x), F.lit(2))), 7).alias("s"))


@query("WITH c AS (SELECT conv_id, turn, role FROM conversations) SELECT a.conv_id, a.turn, count(*) AS n_near FROM c a, LATERAL (SELECT 1 AS one FROM c b WHERE b.conv_id = a.conv_id AND abs(b.turn - a.turn) <= 1) n GROUP BY a.conv_id, a.turn")
def rel_lateral_neighbours(spark, sf_dir):
    t = load(spark, sf_dir, "conversations").select("conv_id", "turn")
    near = t.select("conv_id", "turn", F.explode(F.array(F.col("turn") - 1, F.col("turn"), F.col("turn") + 1)).alias("other"))
    other = t.select("conv_id", F.col("turn").alias("other"))
    return near.join(other, ["conv_id", "other"]).groupBy("conv_id", "turn").agg(F.count(F.lit(1)).alias("n_near"))


@query(f"WITH {cg.sql_vertices(GS, 'g')} SELECT v, b.k AS axis, CASE b.k WHEN 0 THEN a0 WHEN 1 THEN a1 ELSE a2 END AS ix FROM g, (SELECT range AS k FROM range(3)) b")
def rel_array_axes(spark, sf_dir):
    """Array columns to rows: the index of every vertex on every axis."""
    return meshes.vertices(spark, GS).select("v", F.posexplode("ix").alias("axis", "ix")).select("v", F.col("axis").cast("long").alias("axis"), F.col("ix").cast("long").alias("ix"))


@query("SELECT v, k, CAST(row_number() OVER (PARTITION BY k ORDER BY n DESC, v) AS INT) AS place FROM (SELECT l_partkey AS v, CAST(l_partkey % 8 AS INT) AS k, count(*) AS n FROM lineitem GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY k ORDER BY n DESC, v) <= 3")
def rel_rank_best_part(spark, sf_dir):
    """The three heaviest vertices of each part; Spark limits each group before its shuffle."""
    d = load(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("v"), (F.col("l_partkey") % 8).cast("int").alias("k")).agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("k").orderBy(F.desc("n"), "v")
    return d.withColumn("place", F.row_number().over(w)).where("place <= 3").select("v", "k", "place")


# ---- late rows --------------------------------------------------------------------------------------------


@query()
def stream_late_rows(spark, sf_dir):
    """Daily counts of a stream in several batches with a watermark of an hour, next to all rows: the difference was late or is still open."""
    closed = streams.run_to_table(streams.cell_cost(streams.read_events(spark, sf_dir, 1)), "late").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("closed_rows"))
    return closed.crossJoin(load(spark, sf_dir, "events").agg(F.count(F.lit(1)).alias("all_rows")))


@query("SELECT doc_id AS v, CAST(doc_id % 8 AS INT) AS k FROM documents")
def partition_import(spark, sf_dir):
    """A partition that came from elsewhere, as a table."""
    return partition.partition_from_table(load(spark, sf_dir, "documents").select(F.col("doc_id"), (F.col("doc_id") % 8).alias("part")), "doc_id", "part")
