"""Estimates from pairs of signatures, all in generated code."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import theory
from .blocks import compare


def mismatches(k: int, b: int, left: str = "l", right: str = "r", plane: str = "plane_{}") -> Column:
    """Samples whose lowest b bits differ: words are XORed, planes ORed, bits counted."""
    total = None
    for w in range(-(-k // 64)):
        word = None
        for i in range(b):
            c = plane.format(i)
            x = F.col(f"{left}.{c}")[w].bitwiseXOR(F.col(f"{right}.{c}")[w])
            word = x if word is None else word.bitwiseOR(x)
        if k < 64 * (w + 1):
            word = word.bitwiseAND(F.lit((1 << (k - 64 * w)) - 1))
        n = F.bit_count(word)
        total = n if total is None else total + n
    return total.cast("long")


def measured(joined: DataFrame, k: int, b: int, plane: str = "plane_{}") -> DataFrame:
    """id_l, id_r, f_l, f_r, mismatches of joined sides l and r."""
    names = [F.col(f"{side}.{c}").alias(f"{new}_{side}") for new, c in (("id", "set_id"), ("f", "f")) for side in "lr"]
    return joined.select(*names, mismatches(k, b, plane=plane).alias("mismatches"))


def pair_all(sig: DataFrame, k: int, b: int, r0: float | None = None, domain: float | None = None, plane: str = "plane_{}", blocks: int | None = None) -> DataFrame:
    """The same for all pairs of sig, or those whose estimate reaches r0; see blocks.compare."""
    return compare(sig, k, b, r0, domain, plane, blocks)


def densities(domain: float, left: str = "l", right: str = "r") -> tuple[Column, Column]:
    return F.col(f"{left}.f") / F.lit(float(domain)), F.col(f"{right}.f") / F.lit(float(domain))


def _out(pairs: DataFrame, k: int, r_hat, std_err) -> DataFrame:
    matches = (F.lit(k) - F.col("mismatches")).cast("long")
    base = pairs.select("id_l", "id_r", "f_l", "f_r", matches.alias("matches"), (matches / F.lit(float(k))).alias("e_hat"))
    return base.withColumn("r_hat", r_hat(F.col("e_hat"))).withColumn("std_err", std_err(F.col("e_hat"), F.col("r_hat")))


def r_full(pairs: DataFrame, k: int) -> DataFrame:
    """Share of equal minima; pairs carry mismatches of as many planes as minima have bits."""
    return _out(pairs, k, lambda e: e, lambda e, r: F.sqrt(theory.var_full(r, float(k))))


def r_full_minima(full: DataFrame, k: int) -> DataFrame:
    """The same by an equi-join on (j, z): all pairs with at least one equal minimum."""
    z = full.select("set_id", "f", F.posexplode("z").alias("j", "z"))
    l, r = z.alias("l"), z.alias("r")
    j = l.join(r, (F.col("l.j") == F.col("r.j")) & (F.col("l.z") == F.col("r.z")) & (F.col("l.set_id") < F.col("r.set_id")))
    m = j.groupBy(F.col("l.set_id").alias("id_l"), F.col("r.set_id").alias("id_r"), F.col("l.f").alias("f_l"), F.col("r.f").alias("f_r")).agg(F.count("*").alias("matches"))
    return m.withColumn("e_hat", F.col("matches") / F.lit(float(k))).withColumn("r_hat", F.col("e_hat")).withColumn("std_err", F.sqrt(F.col("r_hat") * (1 - F.col("r_hat")) / k))


def r_low(pairs: DataFrame, k: int, b: int, domain: float, clip: bool = False) -> DataFrame:
    """Low-bit estimate with its plug-in standard error; unbiased, so it may leave [0, 1] unless clipped."""

    def r_hat(e):
        floor, slope = theory.floor_slope(F.col("f_l") / F.lit(float(domain)), F.col("f_r") / F.lit(float(domain)), b)
        r = (e - floor) / slope
        return F.greatest(F.lit(0.0), F.least(F.lit(1.0), r)) if clip else r

    def std_err(e, r):
        _, slope = theory.floor_slope(F.col("f_l") / F.lit(float(domain)), F.col("f_r") / F.lit(float(domain)), b)
        return F.sqrt(e * (1 - e) / k) / slope

    return _out(pairs, k, r_hat, std_err)


def with_interval(estimates: DataFrame, z: float = 1.96) -> DataFrame:
    return estimates.withColumn("low", F.col("r_hat") - z * F.col("std_err")).withColumn("high", F.col("r_hat") + z * F.col("std_err"))


def r_fold(pairs: DataFrame, k: int, domain: float, m: int = 2) -> DataFrame:
    """Estimate from folded bits, each of m permutations; where 2T - 1 is negative it is cut to 0, which biases small k."""

    def r_hat(t):
        return theory.r_from_fold(t, F.col("f_l") / F.lit(float(domain)), F.col("f_r") / F.lit(float(domain)), m)

    def std_err(t, r):
        _, slope = theory.floor_slope(F.col("f_l") / F.lit(float(domain)), F.col("f_r") / F.lit(float(domain)), 1)
        return F.when(2 * t > 1, F.sqrt(t * (1 - t) / (m * m * k * slope * slope * F.pow(2 * t - 1, 2 - 2 / m))))

    return _out(pairs, k, r_hat, std_err)


def joint_size(estimates: DataFrame) -> DataFrame:
    """Estimated intersection sizes."""
    return estimates.withColumn("a_hat", theory.joint_size(F.col("r_hat"), F.col("f_l"), F.col("f_r")))


def mismatch_budget(k: int, b: int, r0: float, domain: float, left: str = "l", right: str = "r") -> Column:
    """Most mismatches with which the estimate still reaches r0: an integer test per pair, no inversion."""
    r1, r2 = densities(domain, left, right)
    floor, slope = theory.floor_slope(r1, r2, b)
    return F.floor(F.lit(float(k)) * (1 - floor - slope * r0) + 1e-9)
