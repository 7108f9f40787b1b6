"""Relational operators around the methods: joins, aggregates, windows, set operations, functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, keys: list[str], time: str, value: str, out: str) -> DataFrame:
    """For each left row the last right value of the same keys strictly before it: one union, one window, no range join."""
    row = F.struct(*left.columns)
    empty = F.lit(None).cast(left.select(row.alias("x")).schema["x"].dataType)
    mine = left.select(*keys, F.col(time).alias("_t"), F.lit(1).alias("_s"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), row.alias("_row"))
    theirs = right.select(*keys, F.col(time).alias("_t"), F.lit(0).alias("_s"), F.col(value).alias("_v"), empty.alias("_row"))
    # at equal times left rows come first, so that right rows of the same instant don't count as earlier
    w = Window.partitionBy(*keys).orderBy("_t", F.desc("_s")).rowsBetween(Window.unboundedPreceding, -1)
    last = mine.unionByName(theirs).withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_s = 1")
    return last.select("_row.*", F.col("_last").alias(out))


def interval_join(left: DataFrame, right: DataFrame, keys: list[str], time: str, seconds: int) -> DataFrame:
    """Pairs of rows of the same keys at most ``seconds`` apart, later minus earlier; time is cut into bins of that width,
    so a row meets its own and the next bin only."""
    bin_ = F.floor(F.unix_micros(F.col(time).cast("timestamp")) / (seconds * 1_000_000)).cast("long")
    l = left.withColumn("_bin", F.explode(F.array(bin_, bin_ + 1))).alias("l")
    r = right.withColumn("_bin", bin_).alias("r")
    cond = F.col("l._bin") == F.col("r._bin")
    for k in keys:
        cond = cond & (F.col(f"l.{k}") == F.col(f"r.{k}"))
    gap = F.unix_micros(F.col(f"r.{time}").cast("timestamp")) - F.unix_micros(F.col(f"l.{time}").cast("timestamp"))
    return l.join(r, cond & (gap >= 0) & (gap <= seconds * 1_000_000))


def range_size_join(sizes: DataFrame, r0: float) -> DataFrame:
    """Pairs of sets whose sizes allow resemblance r0: an equi-join on logarithmic bands."""
    import math

    band = F.floor(F.log("f") / -math.log(r0)).cast("int")
    l = sizes.withColumn("_band", F.explode(F.array(band - 1, band, band + 1))).alias("l")
    r = sizes.withColumn("_band", band).alias("r")
    ok = (F.col("l.f") >= r0 * F.col("r.f")) & (F.col("r.f") >= r0 * F.col("l.f")) & (F.col("l.set_id") < F.col("r.set_id"))
    return l.join(r, (F.col("l._band") == F.col("r._band")) & ok).select(F.col("l.set_id").alias("id_l"), F.col("r.set_id").alias("id_r"), F.col("l.f").alias("f_l"), F.col("r.f").alias("f_r"))
