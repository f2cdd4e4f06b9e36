"""Choices between plans that Spark's optimizer cannot make by itself, from sizes known beforehand."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..operators.meshes import MeshSpec


@dataclass(frozen=True)
class Choice:
    name: str
    reason: str


def choose_graph_strategy(spec: MeshSpec | None, rows_per_element: float = 0.0) -> Choice:
    """Arithmetic for box meshes; incidence pairs for data, which are chunked where elements are large."""
    if spec is not None:
        pairs = spec.n_elements * spec.n_ldof**2
        kept = spec.n_vertices * (2 * spec.degree + 1) ** spec.dim
        return Choice("structured", f"{kept} rows without a shuffle instead of {pairs} pairs of incidences")
    return Choice("incidence", "pairs inside elements" + (", in chunks" if rows_per_element > 256 else ""))


def choose_assembly(redundancy: float, ops_per_second: float, entries: float, shuffle_bytes_per_second: float, ops: float) -> Choice:
    """Recompute shared elements on every owner, or compute once and shuffle entries: the cheaper one."""
    extra = (redundancy - 1) * ops / ops_per_second
    move = entries * 24 / shuffle_bytes_per_second
    return Choice("owned", f"{extra:.3g} s of repeated work against {move:.3g} s of shuffle") if extra <= move else Choice("shuffled", f"{move:.3g} s of shuffle against {extra:.3g} s of repeated work")


def choose_solver(n_unknowns: int, limit: int = 3_000) -> Choice:
    return Choice("local", "fits one task") if n_unknowns <= limit else Choice("distributed", "halo-only exchange")


def shuffle_partitions(bytes_: int, target: int = 256 << 20) -> int:
    """Partitions that hold about ``target`` bytes each."""
    return max(1, -(-bytes_ // target))


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def exchanges(df: DataFrame) -> int:
    """Shuffles in the physical plan before adaptive changes."""
    return df._jdf.queryExecution().sparkPlan().toString().count("Exchange") + df._jdf.queryExecution().executedPlan().toString().count("Exchange hash")
