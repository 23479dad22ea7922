"""All queries of the solver and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from blocksolve.operators import solver
from blocksolve.plans import blocks, geometry, operators, streams, workloads
from blocksolve.schema import SolveSpec

MODULES = [blocks, geometry, operators, streams, workloads]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One epoch of averaged block descent on the order-by-supplier system."""
    system = blocks.supplier(spark, sf_dir)
    return solver.epochs_lazily(system, SolveSpec(), 4, [0, 1]).x


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for m in MODULES for k, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: f for m in MODULES for k, f in m.SQL.items()}
