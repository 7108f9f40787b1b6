"""The closed forms and estimators as temporary SQL functions."""

from __future__ import annotations

from pyspark.sql import SparkSession

_BODIES = {
    "residue(r DOUBLE, b INT)": "CASE WHEN r >= 1 THEN 0D WHEN r < 1e-300 THEN power(2D, -b) ELSE exp(ln(r) + (power(2D, b) - 1) * log1p(-r)) / -expm1(power(2D, b) * log1p(-r)) END",
    "floor_b(r1 DOUBLE, r2 DOUBLE, b INT)": "(residue(r1, b) * r2 + residue(r2, b) * r1) / (r1 + r2)",
    "slope_b(r1 DOUBLE, r2 DOUBLE, b INT)": "1 - (residue(r1, b) * r1 + residue(r2, b) * r2) / (r1 + r2)",
    "match_prob(r DOUBLE, r1 DOUBLE, r2 DOUBLE, b INT)": "floor_b(r1, r2, b) + slope_b(r1, r2, b) * r",
    "r_low(e_hat DOUBLE, r1 DOUBLE, r2 DOUBLE, b INT)": "(e_hat - floor_b(r1, r2, b)) / slope_b(r1, r2, b)",
    "r_fold(t_hat DOUBLE, r1 DOUBLE, r2 DOUBLE)": "(sqrt(greatest(2 * t_hat - 1, 0D)) + 1 - 2 * floor_b(r1, r2, 1)) / (2 * slope_b(r1, r2, 1))",
    "var_low(r DOUBLE, r1 DOUBLE, r2 DOUBLE, b INT, k INT)": "match_prob(r, r1, r2, b) * (1 - match_prob(r, r1, r2, b)) / (k * power(slope_b(r1, r2, b), 2))",
    "storage_factor(r DOUBLE, r1 DOUBLE, r2 DOUBLE, b INT)": "b * var_low(r, r1, r2, b, 1)",
}


def register(spark: SparkSession) -> list[str]:
    """Create the functions in the session; returns their names."""
    for head, body in _BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS DOUBLE RETURN {body}")
    return [h.split("(")[0] for h in _BODIES]
