"""Simulations of the estimators on given pairs of sets."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import theory


def draws(spark, pairs: list[dict], reps: int, k: int, seed: int = 1, chunk: int = 50) -> DataFrame:
    """(pair, rep, j, z1, z2): minima of two sets under a random permutation of 0..D-1, drawn from their joint law.

    Under a random permutation only three things matter: the least element of the union (its value and whether it is
    shared or owned by one set), and the next one of the other set.  pairs: dicts with pair, f1, f2, a, D.
    Repetitions are rows, dealt in chunks; generators are seeded by (seed, pair, chunk), so any partitioning draws the same."""
    work = [(p, c) for p in range(len(pairs)) for c in range(-(-reps // chunk))]
    df = spark.createDataFrame(work, "p int, c int").repartition(min(len(work), 64), "p", "c")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p, c in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                q, n = pairs[p], min(chunk, reps - c * chunk) * k
                rng = np.random.default_rng([seed, p, c])
                f1, f2, a, size = q["f1"], q["f2"], q["a"], q["D"]
                union = f1 + f2 - a
                first = least(rng, size, union, n)
                who = rng.integers(0, union, n)
                z1, z2 = first.copy(), first.copy()
                for z, mine, lo, hi in ((z2, f2, a, f1), (z1, f1, f1, union)):  # the first is owned by the other set alone
                    k_own = np.flatnonzero((who >= lo) & (who < hi))
                    if len(k_own):
                        z[k_own] = first[k_own] + 1 + least(rng, size - first[k_own] - 1, mine, len(k_own))
                rep = np.repeat(np.arange(n // k) + c * chunk, k)
                yield pa.RecordBatch.from_arrays([pa.array([q["pair"]] * n), pa.array(rep), pa.array(np.tile(np.arange(k, dtype=np.int32), n // k)), pa.array(z1), pa.array(z2)], ["pair", "rep", "j", "z1", "z2"])

    return df.mapInArrow(run, "pair string, rep long, j int, z1 long, z2 long")


def least(rng, size, marked: int, n: int) -> np.ndarray:
    """Smallest of ``marked`` distinct positions chosen from 0..size-1, n times (size: a number or one per draw)."""
    size = np.broadcast_to(np.asarray(size, np.int64), (n,))
    z, open_ = np.zeros(n, np.int64), np.arange(n)
    while len(open_):
        left = size[open_] - z[open_]
        stop = rng.random(len(open_)) * left < marked
        open_ = open_[~stop]
        z[open_] += 1
    return z


def estimates(drawn: DataFrame, pairs: list[dict], ks: list[int], bs: list[int], fold: bool = False) -> DataFrame:
    """(pair, estimator, b, k, rep, r, r_hat) for every k of the grid; k sums are conditional, one pass over the draws."""
    spark = drawn.sparkSession
    truth = F.broadcast(spark.createDataFrame([(p["pair"], p["f1"] / p["D"], p["f2"] / p["D"], p["a"] / (p["f1"] + p["f2"] - p["a"])) for p in pairs], "pair string, r1 double, r2 double, r double"))
    diff = F.col("z1").bitwiseXOR(F.col("z2"))
    flags = {("full", 32): diff == 0} | {("low", b): diff.bitwiseAND(F.lit((1 << b) - 1)) == 0 for b in bs}
    aggs = [F.sum(F.when((F.col("j") < k) & f, 1).otherwise(0)).alias(f"{e}_{b}_{k}") for (e, b), f in flags.items() for k in ks]
    names = [(e, b, k) for (e, b) in flags for k in ks]
    rows = drawn.groupBy("pair", "rep").agg(*aggs)
    if fold:
        half = max(ks)
        bit = lambda z: F.col(z).bitwiseAND(F.lit(1).cast("long"))
        two = drawn.groupBy("pair", "rep", F.pmod("j", F.lit(half)).alias("t")).agg(F.bit_xor(bit("z1").bitwiseXOR(bit("z2"))).alias("x"))
        rows = rows.join(two.groupBy("pair", "rep").agg(*[F.sum(F.when((F.col("t") < k) & (F.col("x") == 0), 1).otherwise(0)).alias(f"fold_1_{k}") for k in ks]), ["pair", "rep"])
        names += [("fold", 1, k) for k in ks]
    each = F.explode(F.array(*(F.struct(F.lit(e).alias("estimator"), F.lit(b).alias("b"), F.lit(k).alias("k"), (F.col(f"{e}_{b}_{k}") / float(k)).alias("e_hat")) for e, b, k in names))).alias("x")
    out = rows.select("pair", "rep", each).select("pair", "rep", "x.*").join(truth, "pair")

    def low(b):
        floor, slope = theory.floor_slope(F.col("r1"), F.col("r2"), b)
        return (F.col("e_hat") - floor) / slope

    r_hat = F.when(F.col("estimator") == "full", F.col("e_hat")).when(F.col("estimator") == "fold", theory.r_from_fold(F.col("e_hat"), F.col("r1"), F.col("r2")))
    for b in bs:
        r_hat = r_hat.when(F.col("b") == b, low(b))
    return out.withColumn("r_hat", r_hat)


def theory_variance(points: DataFrame) -> DataFrame:
    """Adds the theoretical variance to rows with estimator, b, k, r, r1, r2."""
    r, r1, r2, k = (F.col(c) for c in ("r", "r1", "r2", "k"))
    v = F.when(F.col("estimator") == "full", theory.var_full(r, k)).when(F.col("estimator") == "fold", theory.var_fold(r, r1, r2, k))
    for b in (1, 2, 3, 4):
        v = v.when(F.col("b") == b, theory.var_low(r, r1, r2, b, k))
    return points.withColumn("theory", v)


def bias_mse(spark, pairs: list[dict], ks: list[int], reps: int, bs=(1, 2, 3), fold: bool = False, seed: int = 1) -> DataFrame:
    """pair, estimator, b, k, reps, bias, variance, mse, theory."""
    e = estimates(draws(spark, pairs, reps, max(ks) * (2 if fold else 1), seed), pairs, ks, list(bs), fold)
    d = F.col("r_hat") - F.col("r")
    out = e.groupBy("pair", "estimator", "b", "k", "r", "r1", "r2").agg(F.count("*").alias("reps"), F.avg(d).alias("bias"), F.var_pop("r_hat").alias("variance"), F.avg(d * d).alias("mse"))
    return theory_variance(out).select("pair", "estimator", "b", "k", "reps", "bias", "variance", "mse", "theory")
