"""Functions for SQL users: decay weights as SQL expressions, the planner and the hash family as table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession

from fadegossip.functions.udfs import HashRows, PlanParameters


def register(spark: SparkSession) -> None:
    """Adds decay_linear, decay_exp, decay_half_life, relaxed_threshold (expressions, inlined by the optimizer), plan_parameters and hash_rows."""
    for text in (
        "decay_linear(tick BIGINT, asof BIGINT) RETURNS DOUBLE RETURN CAST(tick AS DOUBLE) / asof",
        "decay_exp(tick BIGINT, asof BIGINT, lam DOUBLE) RETURNS DOUBLE RETURN exp(lam * (tick - asof))",
        "decay_half_life(tick BIGINT, asof BIGINT, half INT) RETURNS DOUBLE RETURN power(2D, CAST(floor(tick / half) - floor(asof / half) AS DOUBLE))",
        "relaxed_threshold(support DOUBLE, total DOUBLE, slack DOUBLE) RETURNS DOUBLE RETURN support * total * (1 - slack) / (1 + slack)",
        "item_fingerprint(item STRING) RETURNS BIGINT RETURN CAST(conv(substring(md5(item), 1, 8), 16, 10) AS BIGINT)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    spark.udtf.register("plan_parameters", PlanParameters)
    spark.udtf.register("hash_rows", HashRows)
