"""The methods' small functions for SQL text: SQL functions where an expression suffices, table functions where rows come out."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .codec.interp import interp_plan

#: Name, parameters, result and body of each SQL function; all are plain expressions that stay in generated code.
FUNCTIONS = (
    ("bezier_mid", "l DOUBLE, c DOUBLE, r DOUBLE", "DOUBLE", "(l + 2 * c + r) / 4"),
    ("clamp_to", "v DOUBLE, center DOUBLE, lim DOUBLE", "DOUBLE", "least(greatest(v, center - lim), center + lim)"),
    ("eb_level", "eb DOUBLE, distance INT, alpha DOUBLE, beta DOUBLE", "DOUBLE", "eb / least(pow(alpha, distance), beta)"),
    ("pad_overhead", "u INT", "DOUBLE", "(u + 1) * (u + 1) / (u * u) - 1"),
    ("block_key", "x INT, y INT, z INT, b INT, nby INT, nbz INT", "BIGINT", "CAST(x div b AS BIGINT) * nby * nbz + (y div b) * nbz + z div b"),
    ("quant_code", "v DOUBLE, pred DOUBLE, eb DOUBLE", "BIGINT", "floor((v - pred) / (2 * eb) + 0.5)"),
    ("zigzag", "q BIGINT", "BIGINT", "CASE WHEN q >= 0 THEN 2 * q ELSE -2 * q - 1 END"),
)


@udtf(returnType="level int, idx int, lo int, hi int, kind string")
class InterpPlan:
    """The plan of a line of n points, one row per point."""

    def eval(self, n: int):
        yield from interp_plan(n)


@udtf(returnType="off int, v double")
class UnpackBlock:
    """The values of a block array with their places."""

    def eval(self, vals: list):
        yield from enumerate(vals or [])


def register(spark: SparkSession) -> None:
    for name, params, result, body in FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {result} RETURN {body}")
    spark.udtf.register("interp_plan", InterpPlan)
    spark.udtf.register("unpack_block", UnpackBlock)
