"""Pair generation: from all pairs to banded candidates, and duplicate classes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import stored
from . import blocks, estimators, exact
from .components import components
from .sets import sizes


def all_pairs(planes: DataFrame, k: int, b: int, r0: float, domain: float, n_blocks: int | None = None) -> DataFrame:
    """Pairs whose estimate reaches r0: every pair is compared, dealt as pairs of blocks."""
    return estimators.r_low(blocks.compare(planes, k, b, r0, domain, blocks=n_blocks), k, b, domain)


def size_filtered(planes: DataFrame, k: int, b: int, r0: float, domain: float) -> DataFrame:
    """As all_pairs, but only pairs whose sizes allow r0 meet: blocks are ranges of sizes."""
    return estimators.r_low(blocks.compare(planes, k, b, r0, domain, ratio=r0), k, b, domain)


def rare_first(sets: DataFrame) -> DataFrame:
    """(set_id, f, alone, elems): what each set shares with any other as one array, its rarest elements first; alone counts the rest.

    Elements of one set alone are its rarest and meet nothing, so only their number matters; a set of these alone has no row.
    Stored, as every step of a prefix join reads it."""
    df = F.count("*").over(Window.partitionBy("elem"))
    each = sets.withColumn("df", df).where("df > 1").groupBy("set_id").agg(F.array_sort(F.collect_list(F.struct("df", "elem"))).alias("e"))  # of one set
    each = each.join(sizes(sets), "set_id").withColumn("f", F.col("f").cast("long"))
    return stored(each.select("set_id", "f", (F.col("f") - F.size("e")).cast("int").alias("alone"), F.transform("e", lambda x: x["elem"]).alias("elems")), "rare-first")


def prefix_candidates(arrays: DataFrame, r0: float) -> DataFrame:
    """(id_l, id_r) that share one of their rarest elements and may still share enough; no pair with r >= r0 is missed."""
    length = (F.col("f") - F.ceil(F.col("f") * r0 - 1e-9) + 1).cast("int")
    met_by = F.slice("elems", 1, F.greatest(length - F.col("alone"), F.lit(0)))
    prefix = arrays.select("set_id", "f", "alone", F.posexplode(met_by).alias("at", "elem")).select("set_id", "f", (F.col("at") + F.col("alone")).alias("at"), "elem")
    l, r = prefix.alias("l"), prefix.alias("r")
    least = F.ceil((F.col("l.f") + F.col("r.f")) * (r0 / (1 + r0)) - 1e-9)
    left = F.least(F.col("l.f") - F.col("l.at"), F.col("r.f") - F.col("r.at"))  # what the sets may share from this element on, it included
    first = F.least("l.at", "r.at")  # and before it, at most
    fits = (F.col("l.f") >= r0 * F.col("r.f")) & (F.col("r.f") >= r0 * F.col("l.f")) & (left + first >= least)
    met = l.join(r, (F.col("l.elem") == F.col("r.elem")) & (F.col("l.set_id") < F.col("r.set_id")) & fits)
    return met.select(F.col("l.set_id").alias("id_l"), F.col("r.set_id").alias("id_r")).distinct()


def prefix_join(sets: DataFrame, r0: float) -> DataFrame:
    """Exact pairs with r >= r0 by prefix candidates and verification of those alone; see exact.common."""
    arrays = rare_first(sets)
    met = stored(prefix_candidates(arrays, r0), "candidates")
    a = exact.common(arrays.select("set_id", F.explode("elems").alias("elem")), met)
    side = lambda s: arrays.select(F.col("set_id").alias(f"id_{s}"), F.col("f").alias(f"f_{s}"))
    a = a.join(side("l"), "id_l").join(side("r"), "id_r").select("id_l", "id_r", "f_l", "f_r", "a")
    return a.withColumn("r", F.col("a") / (F.col("f_l") + F.col("f_r") - F.col("a"))).where(F.col("r") >= r0)


def banded(planes: DataFrame, k: int, b: int, rows: int, r0: float, domain: float, key_bits: int | None = None) -> DataFrame:
    """Candidates that agree on the lowest bits of some band of ``rows`` samples, verified by the estimate on all k at b bits.

    A band catches a pair with probability E^rows, E the match probability at key_bits (b unless given), so rows * key_bits
    should be about log2 of the number of sets or more: below, chance agreement floods the join.  Only ids and keys are
    spread over the bands; a pair met in several bands is compared once."""
    if 64 % rows or k % rows:
        raise ValueError("rows must divide 64 and k")
    mask = F.lit((1 << rows) - 1 if rows < 63 else -1).cast("long")

    def key(t):
        at = t * rows
        return F.xxhash64(t, *(F.call_function("shiftrightunsigned", F.col(f"plane_{i}")[F.floor(at / 64).cast("int")], at % 64).bitwiseAND(mask) for i in range(key_bits or b)))

    keys = F.transform(F.sequence(F.lit(0), F.lit(k // rows - 1)), key)
    each = planes.select("set_id", F.explode(keys).alias("key"))
    l, r = each.alias("l"), each.alias("r")
    met = l.join(r, (F.col("l.key") == F.col("r.key")) & (F.col("l.set_id") < F.col("r.set_id")))
    met = met.select(F.col("l.set_id").alias("id_l"), F.col("r.set_id").alias("id_r")).distinct()
    needed = planes.select("set_id", "f", *(f"plane_{i}" for i in range(b)))
    both = met.join(needed.alias("l"), F.col("id_l") == F.col("l.set_id")).join(needed.alias("r"), F.col("id_r") == F.col("r.set_id"))
    return estimators.r_low(estimators.measured(both, k, b), k, b, domain).where(F.col("r_hat") >= r0 - 1e-9)


def band_recall(R: float, r1: float, r2: float, b: int, rows: int, bands: int) -> float:
    from ..functions import theory

    return 1 - (1 - theory.match_prob(R, r1, r2, b) ** rows) ** bands


def band_rows(R: float, r1: float, r2: float, b: int, k: int, least: float = 0.9) -> int:
    """Most rows a band of k samples may have for a recall of ``least`` at R."""
    for rows in range(min(k, 64), 0, -1):
        if k % rows == 0 and 64 % rows == 0 and band_recall(R, r1, r2, b, rows, k // rows) >= least:
            return rows
    raise ValueError(f"no bands of {k} samples reach a recall of {least} at {R}")


def top_neighbors(pairs: DataFrame, n: int, by: str = "r_hat") -> DataFrame:
    """The n most similar partners of each set, ties to smaller ids."""
    both = pairs.select("id_l", "id_r", by).unionByName(pairs.select(F.col("id_r").alias("id_l"), F.col("id_l").alias("id_r"), by))
    w = Window.partitionBy("id_l").orderBy(F.desc(by), "id_r")
    return both.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n)


def alike(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """((set_id, first): each set and the smallest id of those equal to it, (set_id, elem) of those first ones alone).  Stored."""
    each = sets.groupBy("set_id").agg(F.array_sort(F.collect_list("elem")).alias("e"))  # of one set
    each = each.withColumn("first", F.min("set_id").over(Window.partitionBy(F.md5(F.concat_ws(",", "e")))))
    each = stored(each.select("set_id", "first", F.when(F.col("set_id") == F.col("first"), F.col("e")).alias("e")), "alike")
    return each.select("set_id", "first"), each.select("set_id", F.explode("e").alias("elem"))


def first_alike(each: DataFrame) -> DataFrame:
    """(set_id, first) as alike, of sets (set_id, elems) that are arrays in order; only ids and digests are sent.  Stored."""
    same = each.select("set_id", F.min("set_id").over(Window.partitionBy(F.md5(F.concat_ws(",", "elems")))).alias("first"))
    return stored(same, "alike")


def partners(sets: DataFrame, r0: float) -> DataFrame:
    """set_id of every set that has another one with r >= r0.  Equal sets are one before the join, so copies are never expanded to pairs."""
    same, one = alike(sets)
    e = stored(prefix_join(one, r0).select("id_l", "id_r"), "near")
    near = e.select(F.col("id_l").alias("first")).union(e.select("id_r"))
    copied = same.where("set_id <> first").select("first")
    return same.join(near.union(copied).distinct(), "first", "left_semi").select("set_id")


def copies_join(sets: DataFrame, r0: float) -> DataFrame:
    """As prefix_join, but equal sets are one before the join and are expanded to pairs only in the result."""
    same, one = alike(sets)
    return expanded(same, sizes(one), prefix_join(one, r0), {"a": F.col("f"), "r": F.lit(1.0)})


def expanded(same: DataFrame, f: DataFrame, near: DataFrame, copied: dict[str, Column]) -> DataFrame:
    """Pairs of first ones (id_l, id_r, f_l, f_r and the columns of copied) as pairs of all sets; copied: the values of equal sets, of their size f."""
    l, r = (same.select(F.col("first").alias(f"id_{s}"), F.col("set_id").alias(f"own_{s}")) for s in "lr")
    first = lambda x, y: F.when(F.col("own_l") < F.col("own_r"), F.col(x)).otherwise(F.col(y))
    apart = near.join(l, "id_l").join(r, "id_r").select(first("own_l", "own_r").alias("id_l"), first("own_r", "own_l").alias("id_r"), first("f_l", "f_r").alias("f_l"), first("f_r", "f_l").alias("f_r"), *copied)
    x, y, size = same.alias("x"), same.alias("y"), f.alias("f")
    copies = x.join(y, (F.col("x.first") == F.col("y.first")) & (F.col("x.set_id") < F.col("y.set_id"))).join(size, F.col("x.first") == F.col("f.set_id"))
    copies = copies.select(F.col("x.set_id").alias("id_l"), F.col("y.set_id").alias("id_r"), F.col("f.f").alias("f"))
    return apart.unionByName(copies.select("id_l", "id_r", F.col("f").alias("f_l"), F.col("f").alias("f_r"), *(v.alias(c) for c, v in copied.items())))


def equal_minima(full: DataFrame, k: int, least: int) -> DataFrame:
    """id_l, id_r, a: pairs with ``least`` or more equal minima (set_id, f, z), by a prefix join of sets of k <= 64 minima of 31 bits each; no pair is missed."""
    each = full.select("set_id", F.posexplode("z").alias("j", "z")).select("set_id", (F.col("j") * F.lit(1 << 31) + F.col("z")).alias("elem"))
    return prefix_join(each, least / (2 * k - least)).where(F.col("a") >= least).select("id_l", "id_r", "a")


def duplicate_classes(sets: DataFrame, ids: DataFrame, r0: float) -> DataFrame:
    """set_id, component_id, keep: one set of each class of pairs with r >= r0 is kept.

    Equal sets are one before the join, so copies are never expanded to pairs."""
    same, one = alike(sets)
    e = prefix_join(one, r0).select(F.col("id_l").alias("a"), F.col("id_r").alias("b"))
    e = e.unionByName(same.where("set_id <> first").select(F.col("first").alias("a"), F.col("set_id").alias("b")))
    c = components(e, ids.select(F.col("set_id").alias("node")))
    return c.select(F.col("node").alias("set_id"), F.col("component").alias("component_id"), (F.col("node") == F.col("component")).alias("keep"))
