"""The formulas as SQL functions, whose bodies the analyser puts in line, and a table function."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..operators.planner import best_u_sql

FUNCTIONS = {
    "cov_ratio(e1 BIGINT, l BIGINT)": "try_divide(1.0D, 1 - try_divide(e1, l))",
    "p0_hat(e1 BIGINT, l BIGINT)": "try_divide(e1, l)",
    "rel_var_sampled(p0 DOUBLE, p1 DOUBLE, l BIGINT, m BIGINT, are DOUBLE)": "(p0 * (1 - p0) + p1) / (l * (1 - p0) * (1 - p0)) + 1 / (are * m)",
    "rel_var_subsampled(p0 DOUBLE, p1 DOUBLE, u BIGINT, m BIGINT, are DOUBLE)": "(2 * p0 * (1 - p0) + p1) / (u * (1 - p0) * (1 - p0)) + 1 / (are * m)",
    "expected_sampled(n BIGINT, p0 DOUBLE, p0_mass DOUBLE)": "n * (1 - p0) / (1 - p0_mass)",
    "best_u(b BIGINT, c DOUBLE, are DOUBLE)": best_u_sql("b", "c", "are"),
}


@F.udtf(returnType="m long, u long, rel_var double")
class VarianceGrid:
    """Every split of a budget with its variance."""

    def eval(self, budget: int, p0: float, p1: float) -> Iterator[tuple[int, int, float]]:
        c = (2 * p0 * (1 - p0) + p1) / (1 - p0) ** 2
        for u in range(1, budget - 1):
            yield budget - u, u, c / u + 1 / (budget - u)


def register(spark: SparkSession) -> None:
    for head, body in FUNCTIONS.items():
        kind = "BIGINT" if head.startswith("best_u") else "DOUBLE"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {kind} RETURN {body}")
    spark.udtf.register("variance_grid", VarianceGrid)
