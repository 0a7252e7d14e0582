"""All queries of the engine and their SQL, by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .queries import ops, workloads
from .queries.core import core
from .registry import Query

FAMILIES = (core, workloads.work, ops.ops)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.flagship(spark, sf_dir)


def queries() -> dict[str, Query]:
    return {name: q for family in FAMILIES for name, q in family.queries.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for family in FAMILIES for name, sql in family.sql.items()}
