"""Core, halo and extended sets of a partition, element assignment and the communication plan."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import symmetric


def core_sets(part: DataFrame) -> DataFrame:
    return part.select("k", "v", F.lit(True).alias("is_core"), F.col("k").alias("owner"))


def halo(edges: DataFrame, part: DataFrame) -> DataFrame:
    """Rows (k, v, owner): vertices outside part k with a neighbour in it."""
    e = edges.where("i <> j").select("i", "j")
    pi, pj = part.select(F.col("v").alias("i"), F.col("k").alias("ki")), part.select(F.col("v").alias("j"), F.col("k").alias("kj"))
    cut = e.join(pi, "i").join(pj, "j").where("ki <> kj")
    # both ends of a cut edge are halo of the other's part
    out = cut.select(F.explode(F.array(F.struct(F.col("ki").alias("k"), F.col("j").alias("v"), F.col("kj").alias("owner")), F.struct(F.col("kj").alias("k"), F.col("i").alias("v"), F.col("ki").alias("owner")))).alias("h"))
    return out.select("h.*").distinct()


def extended_sets(edges: DataFrame, part: DataFrame) -> DataFrame:
    return core_sets(part).unionByName(halo(edges, part).withColumn("is_core", F.lit(False)).select("k", "v", "is_core", "owner"))


def extended_subgraph(edges: DataFrame, ext: DataFrame) -> DataFrame:
    """Rows (k, i, j): all edges with both ends in a part's extended set, halo to halo too."""
    a = edges.select("i", "j").join(ext.select(F.col("v").alias("i"), "k"), "i")
    return a.join(ext.select(F.col("v").alias("j"), "k"), ["k", "j"], "left_semi").select("k", "i", "j")


def assign_elements(inc: DataFrame, ext: DataFrame, rule: str = "containment") -> DataFrame:
    """Rows (e, k, n_core): elements whose vertices all lie in the extended set of part k.

    ``rule="owner"`` also asks for a core vertex, leaving out elements that add nothing to owned rows.
    """
    size = inc.groupBy("e").agg(F.count(F.lit(1)).alias("n"))
    met = inc.select("e", "v").join(ext.select("v", "k", "is_core"), "v").groupBy("e", "k").agg(F.count(F.lit(1)).alias("got"), F.count_if("is_core").alias("n_core"))
    out = met.join(size, "e").where("got = n")
    return (out.where("n_core > 0") if rule == "owner" else out).select("e", "k", "n_core")


def cell_incidence(cells: DataFrame, inc_l: DataFrame, inc_g: DataFrame) -> DataFrame:
    """Rows (e, v) where e is the struct of a cell and v runs over the vertices of both its elements."""
    pair = cells.select("e_l", "e_g").distinct()
    cell = F.struct("e_l", "e_g").alias("e")
    a = pair.join(inc_l.select(F.col("e").alias("e_l"), "v"), "e_l").select(cell, "v")
    b = pair.join(inc_g.select(F.col("e").alias("e_g"), "v"), "e_g").select(cell, "v")
    return a.unionByName(b).distinct()


def assign_cells(cells: DataFrame, inc_l: DataFrame, inc_g: DataFrame, ext: DataFrame, rule: str = "containment") -> DataFrame:
    """Rows (e_l, e_g, k, n_core): the same for the pieces of coupling work."""
    return assign_elements(cell_incidence(cells, inc_l, inc_g), ext, rule).select("e.e_l", "e.e_g", "k", "n_core")


def shared_elements(assigned: DataFrame) -> DataFrame:
    """Rows (e, n_parts) of elements that several parts evaluate."""
    return assigned.groupBy("e").agg(F.count(F.lit(1)).alias("n_parts")).where("n_parts > 1")


def comm_plan(halo_: DataFrame) -> DataFrame:
    """Rows (k_to, k_from, v): what each part receives, from adjacency alone."""
    return halo_.select(F.col("k").alias("k_to"), F.col("owner").alias("k_from"), "v")


def comm_summary(plan: DataFrame) -> DataFrame:
    return plan.groupBy("k_to").agg(F.countDistinct("k_from").alias("n_neighbours"), F.count(F.lit(1)).alias("n_values"))


def missing_rows(inc: DataFrame, part: DataFrame, assigned: DataFrame) -> DataFrame:
    """Elements with a core vertex of k that are not assigned to k; empty for a correct assignment."""
    need = inc.select("e", "v").join(part, "v").select("e", "k").distinct()
    return need.join(assigned, ["e", "k"], "left_anti")


def redundancy(assigned: DataFrame, n_elements: int) -> DataFrame:
    return assigned.agg((F.count(F.lit(1)) / n_elements).alias("redundancy"))


def neighbours(edges: DataFrame) -> DataFrame:
    return symmetric(edges)
