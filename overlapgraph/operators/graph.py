"""The support-overlap graph: an edge wherever two basis functions are not zero at one place.

Edges are kept once, ``i <= j``, with self-edges; ``kind`` names the meshes (GG, LL, GL).
"""

from __future__ import annotations

from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import store
from .geometry import TOLERANCE
from .meshes import MeshSpec, digits, encode, incidence

#: An element's vertex list is paired in chunks of about this many vertices.
CHUNK = 256


def offsets(spark: SparkSession, reach: int, dim: int) -> DataFrame:
    """The neighbour offsets within ``reach`` per axis: (2 reach + 1)^dim rows at any mesh size."""
    return spark.createDataFrame([(list(d),) for d in product(range(-reach, reach + 1), repeat=dim)], "d array<int>")


def graph_structured(spark: SparkSession, spec: MeshSpec, both: bool = False, kind: str | None = None) -> DataFrame:
    """Graph of one box mesh by index arithmetic: vertices times offsets, no join and no shuffle.

    Splines overlap when their indices differ by the degree at most on each axis. Lagrange
    functions overlap when they share an element, which the second test checks for orders above one.
    """
    p, dim = spec.degree, spec.dim
    base = spark.range(spec.n_vertices).withColumnRenamed("id", "a").crossJoin(F.broadcast(offsets(spark, p, dim)))
    ix = digits("a", spec.n_cp)
    jx = [ix[k] + F.col("d")[k] for k in range(dim)]
    ok = reduce(lambda x, y: x & y, [(jx[k] >= 0) & (jx[k] < spec.n_cp[k]) for k in range(dim)])
    if spec.family == "lagrange" and p > 1:
        first = lambda c: F.greatest(F.lit(0), F.ceil(c / p) - 1)
        last = lambda c, n: F.least(F.lit(n - 1), F.floor(c / p))
        ok = ok & reduce(lambda x, y: x & y, [F.greatest(first(ix[k]), first(jx[k])) <= F.least(last(ix[k], spec.n_el[k]), last(jx[k], spec.n_el[k])) for k in range(dim)])
    out = base.where(ok).select((F.col("a") + spec.offset).alias("i"), (encode(jx, spec.n_cp) + spec.offset).alias("j"))
    return (out if both else out.where("i <= j")).withColumn("kind", F.lit(kind or spec.mesh * 2))


def host_ranges(local: MeshSpec, g: MeshSpec, tol: float = TOLERANCE) -> list[tuple[Column, Column]]:
    """Per axis, the range of global indices whose splines overlap a local vertex's support."""
    ix = digits("id", local.n_cp)
    p, out = local.degree, []
    for a in range(g.dim):
        lo = F.lit(local.lo[a]) + F.greatest(F.lit(0), F.ceil(ix[a] / p) - 1) * local.h[a]
        hi = F.lit(local.lo[a]) + F.least(F.lit(local.n_el[a]), F.floor(ix[a] / p) + 1) * local.h[a]
        first = F.greatest(F.lit(0), F.floor((lo - g.lo[a]) / g.h[a] + tol))
        last = F.least(F.lit(g.n_el[a] - 1), F.ceil((hi - g.lo[a]) / g.h[a] - tol) - 1)
        out.append((first.cast("int"), (last + g.degree).cast("int")))
    return out


def graph_between(spark: SparkSession, local: MeshSpec, g: MeshSpec) -> DataFrame:
    """Inter-mesh edges by exact overlap: each local vertex names its span range; no join, no shuffle."""
    ranges = host_ranges(local, g)
    out = spark.range(local.n_vertices).select(F.col("id"), *[F.sequence(a, b).alias(f"r{k}") for k, (a, b) in enumerate(ranges)])
    for k in range(g.dim):
        out = out.withColumn(f"r{k}", F.explode(f"r{k}"))
    gi = encode([F.col(f"r{k}") for k in range(g.dim)], g.n_cp) + g.offset
    li = F.col("id") + local.offset
    return out.select(F.least(gi, li).alias("i"), F.greatest(gi, li).alias("j"), F.lit("GL").alias("kind"))


def graph_overlay(spark: SparkSession, g: MeshSpec, *locals_: MeshSpec, mode: str = "exact", cells: DataFrame | None = None) -> DataFrame:
    """Graph of a global mesh and local meshes: inside each mesh, and across by the same rule.

    ``mode="sampled"`` takes the inter-mesh edges from the cells of a coupling map instead.
    """
    parts = [graph_structured(spark, g, kind="GG")]
    for local in locals_:
        parts.append(graph_structured(spark, local, kind="LL"))
        parts.append(graph_between(spark, local, g) if mode == "exact" else graph_from_cells(cells, incidence(spark, local), incidence(spark, g)))
    return reduce(DataFrame.unionByName, parts)


def graph_from_incidence(inc: DataFrame, kind: str = "GG", chunk: int = CHUNK) -> DataFrame:
    """Graph of any mesh given as rows (e, v): two vertices of one element are neighbours.

    An element that very many vertices share is cut into chunks, and each chunk meets each chunk as a
    task of its own, so no element's pairs are made in one place. Nothing is capped.
    """
    size = inc.groupBy("e").agg(F.ceil(F.count(F.lit(1)) / chunk).cast("int").alias("fan"))
    cut = inc.select("e", "v").join(size, "e").withColumn("part", F.pmod(F.xxhash64("v"), F.col("fan")).cast("int"))
    a = cut.select("e", F.col("v").alias("i"), F.col("part").alias("pi"), F.explode(F.sequence(F.lit(0), F.col("fan") - 1)).alias("pj"))
    b = cut.select("e", F.col("v").alias("j"), F.col("part").alias("pj"), F.explode(F.sequence(F.lit(0), F.col("fan") - 1)).alias("pi"))
    return a.join(b, ["e", "pi", "pj"]).where("i <= j").select("i", "j").distinct().withColumn("kind", F.lit(kind))


def graph_of_classes(inc: DataFrame) -> DataFrame:
    """The same graph with vertices alike taken together: rows (i, j, kind), whose size does not follow the square of a class.

    Vertices of exactly the same shared elements are one class, named by its smallest vertex: they have the same neighbours and are neighbours
    themselves. ``member`` rows name each vertex j of class i (also i itself), ``link`` rows two classes i < j with a common element, all of whose
    vertices are neighbours. Vertices whose elements nobody shares have no edge and no row. Elements are told apart by their SHA-256.
    """
    hashed = inc.select(F.unhex(F.sha2(F.col("e").cast("string"), 256)).alias("e"), "v").distinct()
    hashed = store(hashed, "class-elements")
    common = hashed.groupBy("e").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("e")
    shared = store(hashed.join(common, "e", "left_semi"), "class-shared")
    alike = shared.groupBy("v").agg(F.sha2(F.array_join(F.transform(F.sort_array(F.collect_list("e")), F.hex), ""), 256).alias("s"))
    alike = store(alike, "class-alike")
    classes = alike.groupBy("s").agg(F.min("v").alias("i"))
    members = alike.join(classes, "s").select("i", F.col("v").alias("j"), F.lit("member").alias("kind"))
    links = graph_from_incidence(shared.join(classes.select(F.col("i").alias("v")), "v", "left_semi"), "link").where("i <> j")
    return links.unionByName(members)


def graph_from_cells(cells: DataFrame, inc_local: DataFrame, inc_global: DataFrame) -> DataFrame:
    """Inter-mesh edges as the cells (e_l, e_g) show them: every pair of their vertices."""
    a = cells.select("e_l", "e_g").distinct()
    b = a.join(inc_local.select(F.col("e").alias("e_l"), F.col("v").alias("vl")), "e_l").select("e_g", "vl").distinct()
    c = b.join(inc_global.select(F.col("e").alias("e_g"), F.col("v").alias("vg")), "e_g")
    return c.select(F.least("vg", "vl").alias("i"), F.greatest("vg", "vl").alias("j")).distinct().withColumn("kind", F.lit("GL"))


def support_graph(sup: DataFrame, width: float, tol: float = TOLERANCE) -> DataFrame:
    """Graph of arbitrary support boxes (v, lo, hi): binned join on the first axis, exact test, each pair once.

    ``width`` is the bin width; a pair is kept in the bin where the later of the two boxes begins.
    """
    first = lambda c: F.floor(c / width).cast("long")
    copied = sup.withColumn("bin", F.explode(F.sequence(first(F.col("lo")[0]), first(F.col("hi")[0] - tol))))
    a = copied.select("bin", F.col("v").alias("i"), F.col("lo").alias("lo_i"), F.col("hi").alias("hi_i"))
    b = copied.select("bin", F.col("v").alias("j"), F.col("lo").alias("lo_j"), F.col("hi").alias("hi_j"))
    meet = F.forall(F.arrays_zip("lo_i", "hi_i", "lo_j", "hi_j"), lambda z: (z["lo_i"] + tol < z["hi_j"]) & (z["lo_j"] + tol < z["hi_i"]))
    once = F.col("bin") == first(F.greatest(F.col("lo_i")[0], F.col("lo_j")[0]))
    return a.join(b, "bin").where((F.col("i") <= F.col("j")) & meet & once).select("i", "j")


def support_graph_bruteforce(sup: DataFrame, tol: float = TOLERANCE) -> DataFrame:
    """All pairs of supports tested one by one; for tests only."""
    a = sup.select(F.col("v").alias("i"), F.col("lo").alias("lo_i"), F.col("hi").alias("hi_i"))
    b = sup.select(F.col("v").alias("j"), F.col("lo").alias("lo_j"), F.col("hi").alias("hi_j"))
    meet = F.forall(F.arrays_zip("lo_i", "hi_i", "lo_j", "hi_j"), lambda z: (z["lo_i"] + tol < z["hi_j"]) & (z["lo_j"] + tol < z["hi_i"]))
    return a.crossJoin(b).where((F.col("i") <= F.col("j")) & meet).select("i", "j")


def graph_without_coupling(edges: DataFrame) -> DataFrame:
    """Baseline: the meshes as if each stood alone."""
    return edges.where("kind <> 'GL'")


def symmetric(edges: DataFrame) -> DataFrame:
    """Both directions of every edge, self-edges once."""
    return edges.select("i", "j").unionByName(edges.where("i <> j").select(F.col("j").alias("i"), F.col("i").alias("j")))


def candidate_pattern(edges: DataFrame) -> DataFrame:
    """The stored pattern of the matrix: all pairs of neighbours, whether their entry is zero or not."""
    return symmetric(edges)


def graph_stats(edges: DataFrame) -> DataFrame:
    """Counts by kind and in all: stored edges, without self-edges, and matrix entries."""
    return edges.rollup("kind").agg(
        F.count(F.lit(1)).alias("n_edges"), F.count_if(F.col("i") != F.col("j")).alias("n_edges_noself"),
        F.sum(F.when(F.col("i") == F.col("j"), 1).otherwise(2)).cast("long").alias("nnz"),
    ).withColumn("kind", F.coalesce("kind", F.lit("all")))


def degrees(edges: DataFrame) -> DataFrame:
    return symmetric(edges).groupBy(F.col("i").alias("v")).agg(F.count_if(F.col("i") != F.col("j")).alias("degree"))
