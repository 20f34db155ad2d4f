"""All queries of the engine and the SQL they are held against."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

import crowding.operators.relational  # noqa: F401  registers
import crowding.plans.methods  # noqa: F401  registers
from crowding.plans import measures, solver
from crowding.plans.registry import ORACLES, QUERIES
from crowding.plans.workloads import parts_together


def queries():
    return QUERIES


def oracle_sql() -> dict[str, str]:
    return ORACLES


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.table_lines(solver.solve_graphs(spark, {"parts": parts_together(spark, sf_dir)}, (5,)))
