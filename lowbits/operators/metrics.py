"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def bias_mse(estimates: DataFrame, keys: list[str], truth: str = "r", guess: str = "r_hat") -> DataFrame:
    """reps, bias, variance and mse by keys."""
    e = F.col(guess) - F.col(truth)
    return estimates.groupBy(*keys).agg(F.count("*").alias("reps"), F.avg(e).alias("bias"), F.var_pop(guess).alias("variance"), F.avg(e * e).alias("mse"))


def precision_recall(pairs: DataFrame, thresholds: list[float], keys: list[str], truth: str = "r", guess: str = "r_hat") -> DataFrame:
    """n_rel, n_ret, n_hit, precision, recall by keys and r0.  pairs: truth and guess of every pair that reaches some threshold in either."""
    spark = pairs.sparkSession
    r0 = F.broadcast(spark.createDataFrame([(float(t),) for t in thresholds], "r0 double"))
    rel, ret = F.coalesce(F.col(truth) >= F.col("r0"), F.lit(False)), F.coalesce(F.col(guess) >= F.col("r0"), F.lit(False))
    counts = pairs.crossJoin(r0).groupBy(*keys, "r0").agg(F.count_if(rel).alias("n_rel"), F.count_if(ret).alias("n_ret"), F.count_if(rel & ret).alias("n_hit"))
    return with_ratios(counts)


def with_ratios(counts: DataFrame) -> DataFrame:
    """Adds precision and recall to n_rel, n_ret, n_hit; null where nothing is retrieved or relevant."""
    ratio = lambda n: F.when(F.col(n) > 0, F.col("n_hit") / F.col(n))
    return counts.withColumn("precision", ratio("n_ret")).withColumn("recall", ratio("n_rel"))


def required_k(curve: DataFrame, target: float, keys: list[str]) -> DataFrame:
    """Smallest k of the grid from which the target precision is reached (null: never)."""
    return curve.groupBy(*keys).agg(F.min(F.when(F.col("precision") >= target, F.col("k"))).alias("k"))


def space_gain(curve: DataFrame, targets: list[float], full_bits: int = 32) -> DataFrame:
    """r0, target, b, k_low, k_full, gain = full_bits k_full / (b k_low)."""
    out = None
    for t in targets:
        need = required_k(curve, t, ["estimator", "b", "r0"])
        full = need.where("estimator = 'full'").select("r0", F.col("k").alias("k_full"))
        low = need.where("estimator = 'low'").select("r0", "b", F.col("k").alias("k_low"))
        g = low.join(full, "r0").select("r0", F.lit(float(t)).alias("target"), "b", "k_low", "k_full", (F.lit(float(full_bits)) * F.col("k_full") / (F.col("b") * F.col("k_low"))).alias("gain"))
        out = g if out is None else out.unionByName(g)
    return out
