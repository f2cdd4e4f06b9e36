"""Vertex weights from the operation counts of matrix generation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def uniform_weights(vertex: DataFrame) -> DataFrame:
    return vertex.select("v", F.lit(1.0).alias("w"))


def element_ops(inc: DataFrame, n_ip: int, d: int = 1) -> DataFrame:
    """Rows (e, n_ldof, ops): operations of one element's own matrix, for any number of vertices per element."""
    return inc.groupBy("e").agg(F.count(F.lit(1)).alias("n_ldof")).withColumn("ops", (F.lit(float(n_ip * d * d)) * F.col("n_ldof") * F.col("n_ldof")))


def cell_ops(cells: DataFrame, el: DataFrame, eg: DataFrame, n_ip: int, d: int = 1) -> DataFrame:
    """Rows (e_l, e_g, m_e, nl, ng, ops): a local element's coupling cost, split over the elements it crosses.

    Both coupling blocks are in one figure. A cell uses the size of its own global element.
    """
    m = cells.groupBy("e_l").agg(F.count(F.lit(1)).alias("m_e"))
    sized = cells.join(m, "e_l").join(el.select(F.col("e").alias("e_l"), F.col("n_ldof").alias("nl")), "e_l").join(eg.select(F.col("e").alias("e_g"), F.col("n_ldof").alias("ng")), "e_g")
    return sized.select("e_l", "e_g", "m_e", "nl", "ng", (F.lit(float(n_ip * d * d)) * F.col("nl") * F.col("ng") / F.col("m_e")).alias("ops"))


def weight_components(inc_g: DataFrame, inc_l: DataFrame, cells: DataFrame, n_ip: int, d: int = 1) -> DataFrame:
    """Rows (v, w_gg, w_ll, w_c): one aggregation that serves every choice of coefficients.

    An element's cost is spread evenly over its vertices; half of a cell's cost goes to the local
    and half to the global vertices. Cells are summed by global element before its vertices are joined.
    """
    eg, el = element_ops(inc_g, n_ip, d), element_ops(inc_l, n_ip, d)
    cells = cell_ops(cells.select("e_l", "e_g").distinct(), el, eg, n_ip, d)
    at_g = cells.groupBy(F.col("e_g").alias("e")).agg(F.sum("ops").alias("c"))
    at_l = cells.groupBy(F.col("e_l").alias("e")).agg(F.sum("ops").alias("c"))
    own_g = eg.join(at_g, "e", "left").select("e", (F.col("ops") / F.col("n_ldof")).alias("own"), (F.coalesce("c", F.lit(0.0)) / 2 / F.col("n_ldof")).alias("w_c"))
    own_l = el.join(at_l, "e", "left").select("e", (F.col("ops") / F.col("n_ldof")).alias("own"), (F.coalesce("c", F.lit(0.0)) / 2 / F.col("n_ldof")).alias("w_c"))
    zero = F.lit(0.0)
    rows = inc_g.join(own_g, "e").select("v", F.col("own").alias("w_gg"), zero.alias("w_ll"), "w_c").unionByName(
        inc_l.join(own_l, "e").select("v", zero.alias("w_gg"), F.col("own").alias("w_ll"), "w_c")
    )
    return rows.groupBy("v").agg(F.sum("w_gg").alias("w_gg"), F.sum("w_ll").alias("w_ll"), F.sum("w_c").alias("w_c"))


def combine(components: DataFrame, alpha: tuple[float, float, float]) -> DataFrame:
    """Weights of one choice of coefficients."""
    a, b, c = alpha
    return components.select("v", (F.col("w_gg") * a + F.col("w_ll") * b + F.col("w_c") * c).alias("w"))


def alpha_sweep(components: DataFrame, third: tuple[float, ...] = (20.0, 40.0, 60.0, 80.0)) -> DataFrame:
    """Rows (alpha3, v, w): all choices from one aggregation, as weights are linear in the coefficients."""
    choice = F.explode(F.array(*[F.lit(float(a)) for a in third])).alias("alpha3")
    return components.select("v", "w_gg", "w_ll", "w_c", choice).select("alpha3", "v", (F.col("w_gg") + F.col("w_ll") + F.col("alpha3") * F.col("w_c")).alias("w"))


def weight_audit(components: DataFrame, inc_g: DataFrame, inc_l: DataFrame, cells: DataFrame, n_ip: int, d: int = 1) -> DataFrame:
    """One row: the sums over vertices and over elements, which must agree."""
    eg, el = element_ops(inc_g, n_ip, d), element_ops(inc_l, n_ip, d)
    ce = cell_ops(cells.select("e_l", "e_g").distinct(), el, eg, n_ip, d)
    by_v = components.agg(F.sum("w_gg").alias("v_gg"), F.sum("w_ll").alias("v_ll"), F.sum("w_c").alias("v_c"))
    return by_v.crossJoin(eg.agg(F.sum("ops").alias("e_gg"))).crossJoin(el.agg(F.sum("ops").alias("e_ll"))).crossJoin(ce.agg(F.sum("ops").alias("e_c")))


def tune_alpha(costs: DataFrame) -> DataFrame:
    """The coefficient of least makespan among modelled runs (alpha3, n_dom, k, total)."""
    span = costs.groupBy("n_dom", "alpha3").agg(F.max("total").alias("makespan"))
    return span.groupBy("n_dom").agg(F.min_by("alpha3", F.struct("makespan", "alpha3")).alias("alpha3"), F.min("makespan").alias("makespan"))
