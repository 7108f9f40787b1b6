"""Exact similarity: the ground truth."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.io import stored
from . import blocks
from .sets import sizes

#: Elements of a range: fewer are not worth a task, more are too many for one.  Bytes of a range's bitmaps, words held at a time, rows of a batch sent.
LEAST_ELEMENTS, MOST_ELEMENTS = 1 << 16, 1 << 22
BITMAP_BYTES, CELLS, ROWS_OUT = 64 << 20, 1 << 20, 1 << 16
#: Sets so few that their ids are sent to every task.
FEW = 1 << 17


def intersections(sets: DataFrame, min_overlap: int = 1) -> DataFrame:
    """(id_l, id_r, a) of all pairs that share an element: inverted-list join.  Its cost is quadratic in an element's frequency."""
    l, r = sets.select(F.col("set_id").alias("id_l"), "elem"), sets.select(F.col("set_id").alias("id_r"), "elem")
    a = l.join(r, "elem").where("id_l < id_r").groupBy("id_l", "id_r").agg(F.count("*").alias("a"))
    return a.where(F.col("a") >= min_overlap) if min_overlap > 1 else a


def resemblance(sets: DataFrame, r0: float | None = None) -> DataFrame:
    """id_l, id_r, f_l, f_r, a, r of all pairs that share an element (at least r0, if given)."""
    f = sizes(sets)
    out = intersections(sets).join(f.select(F.col("set_id").alias("id_l"), F.col("f").alias("f_l")), "id_l").join(f.select(F.col("set_id").alias("id_r"), F.col("f").alias("f_r")), "id_r")
    out = out.select("id_l", "id_r", "f_l", "f_r", "a", (F.col("a") / (F.col("f_l") + F.col("f_r") - F.col("a"))).alias("r"))
    return out.where(F.col("r") >= r0) if r0 is not None else out


def common(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """id_l, id_r, a of the given pairs (id_l, id_r), each once.

    Elements are dealt into ranges; a task holds the elements of one range with all pairs and counts what they share there, so
    what is sent is every element once and every pair once for each range, never a set for each of its pairs.  Where pairs are of few sets, only
    the elements of these are sent; ranges are no more than make the pairs sent as many as the elements, unless a range would be too large."""
    spark, kind = sets.sparkSession, sets.schema["set_id"].dataType.simpleString()
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)
    given = pairs.count()
    named = pairs.select(F.col("id_l").alias("set_id")).union(pairs.select("id_r")).distinct()
    if 2 * given <= FEW or named.count() <= FEW:
        sets = sets.join(F.broadcast(named), "set_id", "left_semi")
    n = sets.count()
    ranges = max(1, math.ceil(n / MOST_ELEMENTS), min(tasks, math.ceil(n / LEAST_ELEMENTS), math.ceil(n / max(1, given))))
    ids = sets.schema["set_id"].dataType
    every = F.explode(F.sequence(F.lit(0), F.lit(ranges - 1)))
    wanted = pairs.select("id_l", "id_r").distinct().select(every.alias("range"), F.col("id_l").cast(ids).alias("x"), F.col("id_r").cast(ids).alias("y"), F.lit(None).cast(sets.schema["elem"].dataType).alias("elem"))
    held = sets.select(F.pmod(F.xxhash64("elem"), F.lit(ranges)).cast("int").alias("range"), F.col("set_id").alias("x"), F.lit(None).cast(ids).alias("y"), "elem")
    dealt = held.unionByName(wanted).repartition(ranges, "range").sortWithinPartitions("range")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, rows = None, []
        for batch in batches:
            r = batch.column(0).to_numpy()
            cut = [0, *(np.flatnonzero(np.diff(r)) + 1).tolist(), len(r)]
            for lo, hi in zip(cut, cut[1:]):
                if hi > lo:
                    if rows and key != r[lo]:
                        yield from shared(pa.Table.from_batches(rows), key == 0)
                        rows = []
                    key = r[lo]
                    rows.append(batch.slice(lo, hi - lo))
        if rows:
            yield from shared(pa.Table.from_batches(rows), key == 0)

    return dealt.mapInArrow(run, f"id_l {kind}, id_r {kind}, a long").groupBy("id_l", "id_r").agg(F.sum("a").alias("a"))


def of_few(sets: DataFrame) -> DataFrame:
    """id_l < id_r, f_l, f_r, a, r of all pairs of sets that share an element, for sets so few that a task holds a count for each pair of them.

    Elements are dealt to tasks; each counts the pairs among its own and sends one row of counts for each set, so nothing is sent for
    a pair and an element they share, and only the sets' ids come to the driver."""
    spark, kind = sets.sparkSession, sets.schema["set_id"].dataType.simpleString()
    ids = sorted(r.set_id for r in sets.select("set_id").distinct().collect())  # bounded by the caller
    n = len(ids)
    tasks = max(2 * spark.sparkContext.defaultParallelism, math.ceil(sets.count() / MOST_ELEMENTS))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not sum(b.num_rows for b in held):
            return
        rows = pa.Table.from_batches(held)
        s = pc.index_in(rows.column("set_id").combine_chunks(), pa.array(ids, rows.schema.field("set_id").type)).to_numpy().astype(np.int64)
        e = rows.column("elem").combine_chunks().dictionary_encode()
        size = np.bincount(s, minlength=n)
        l, r = np.triu_indices(n, 1)
        a, lo = overlaps(s, e.indices.to_numpy().astype(np.int64), n, len(e.dictionary), l, r), 0
        for x in range(n):  # of each set: its size, then what it shares with all that follow
            hi = lo + n - 1 - x
            yield pa.RecordBatch.from_arrays([pa.array([x], pa.int32()), pa.array([np.r_[size[x], a[lo:hi]]], pa.list_(pa.int64()))], ["x", "a"])
            lo = hi

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, a = -1, np.zeros(0, np.int64)

        def out() -> pa.RecordBatch:
            y = np.flatnonzero(a)
            return pa.RecordBatch.from_arrays([pa.array([ids[x]] * len(y)), pa.array([ids[x + i] for i in y]), pa.array(a[y])], ["id_l", "id_r", "a"])

        for b in batches:
            values, start = b.column(1).flatten().to_numpy(), np.r_[0, np.cumsum(pc.list_value_length(b.column(1)).to_numpy())]
            for i, own in enumerate(b.column(0).to_pylist()):
                if own != x:
                    if x >= 0:
                        yield out()
                    x, a = own, np.zeros(n - own, np.int64)
                a += values[start[i] : start[i + 1]]
        if x >= 0:
            yield out()

    dealt = sets.select("set_id", "elem").repartition(tasks, "elem").mapInArrow(count, "x int, a array<long>")
    counted = stored(dealt.repartition("x").sortWithinPartitions("x").mapInArrow(total, f"id_l {kind}, id_r {kind}, a long"), "counted")
    f = counted.where("id_l = id_r")
    side = lambda s: f.select(F.col("id_l").alias(f"id_{s}"), F.col("a").alias(f"f_{s}"))
    out = counted.where("id_l <> id_r").join(F.broadcast(side("l")), "id_l").join(F.broadcast(side("r")), "id_r")
    return out.select("id_l", "id_r", "f_l", "f_r", "a", (F.col("a") / (F.col("f_l") + F.col("f_r") - F.col("a"))).alias("r"))


def of_pairs(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """id_l, id_r, f_l, f_r, a, r of the given pairs (id_l, id_r) alone."""
    f = sizes(sets)
    out = pairs.select("id_l", "id_r").join(common(sets, pairs), ["id_l", "id_r"])
    out = out.join(f.select(F.col("set_id").alias("id_l"), F.col("f").alias("f_l")), "id_l").join(f.select(F.col("set_id").alias("id_r"), F.col("f").alias("f_r")), "id_r")
    return out.select("id_l", "id_r", "f_l", "f_r", "a", (F.col("a") / (F.col("f_l") + F.col("f_r") - F.col("a"))).alias("r"))


def shared(rows: pa.Table, all_rows: bool) -> Iterator[pa.RecordBatch]:
    """id_l, id_r, a of the pairs among rows (y is set) over the elements among them; all_rows: pairs that share nothing too."""
    is_pair = pc.is_valid(rows.column("y"))
    pairs, held = rows.filter(is_pair), rows.filter(pc.invert(is_pair))
    if not pairs.num_rows:
        return
    x, y = pairs.column("x").combine_chunks(), pairs.column("y").combine_chunks()
    a = np.zeros(len(x), np.int64)
    if held.num_rows:
        of_set, of_elem = (held.column(c).combine_chunks().dictionary_encode() for c in ("x", "elem"))
        at = lambda ids: pc.fill_null(pc.index_in(ids, of_set.dictionary), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        l, r = at(x), at(y)
        known = np.flatnonzero((l >= 0) & (r >= 0))
        s, e = of_set.indices.to_numpy().astype(np.int64), of_elem.indices.to_numpy().astype(np.int64)
        often = np.bincount(e) > 1  # what only one set has is shared by no pair
        s, e = s[often[e]], (np.cumsum(often) - 1)[e[often[e]]]
        if len(s) and len(known):
            a[known] = overlaps(s, e, len(of_set.dictionary), int(often.sum()), l[known], r[known])
    keep = np.arange(len(a)) if all_rows else np.flatnonzero(a)
    for lo in range(0, len(keep), ROWS_OUT):
        i = pa.array(keep[lo : lo + ROWS_OUT])
        yield pa.RecordBatch.from_arrays([x.take(i), y.take(i), pa.array(a[keep[lo : lo + ROWS_OUT]])], ["id_l", "id_r", "a"])


def overlaps(s: np.ndarray, e: np.ndarray, sets: int, elems: int, l: np.ndarray, r: np.ndarray) -> np.ndarray:
    """How many elements the sets l and r share, pair by pair; (s, e) are the distinct members.  Bitmaps where they fit, else sorted keys."""
    out, words = np.zeros(len(l), np.int64), -(-elems // 64)
    if sets * words * 8 <= BITMAP_BYTES:
        at = s * words + (e >> 6)
        order = np.argsort(at, kind="stable")
        at, bit = at[order], np.uint64(1) << (e[order] & 63).astype(np.uint64)
        first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
        bits = np.zeros(sets * words, np.uint64)
        bits[at[first]] = np.bitwise_or.reduceat(bit, first)
        bits, step = bits.reshape(sets, words), max(1, CELLS // words)
        for lo in range(0, len(l), step):
            out[lo : lo + step] = np.bitwise_count(bits[l[lo : lo + step]] & bits[r[lo : lo + step]]).sum(axis=1, dtype=np.int64)
        return out
    keys = np.sort(s * elems + e)
    start = np.searchsorted(keys, np.arange(sets + 1) * elems)
    size = np.diff(start)
    swap = size[l] > size[r]
    few, many = np.where(swap, r, l), np.where(swap, l, r)  # members of the smaller set are looked up in the larger one
    total = np.r_[0, np.cumsum(size[few])]
    lo = 0
    while lo < len(l):
        hi = max(lo + 1, int(np.searchsorted(total, total[lo] + CELLS, "right")) - 1)
        n = size[few[lo:hi]]
        pair = np.repeat(np.arange(hi - lo), n)
        own = np.arange(len(pair)) - np.repeat(total[lo:hi] - total[lo], n) + start[few[lo:hi]][pair]
        wanted = keys[own] % elems + many[lo:hi][pair] * elems
        found = np.searchsorted(keys, wanted)
        hit = keys[np.minimum(found, len(keys) - 1)] == wanted
        out[lo:hi] = np.bincount(pair[hit], minlength=hi - lo)
        lo = hi
    return out


def members(sets: DataFrame) -> DataFrame:
    """(set_id, f, elems): each set with its elements as one array.  Stored."""
    each = sets.groupBy("set_id").agg(F.count("*").alias("f"), F.array_sort(F.collect_list("elem")).alias("elems"))  # of one set
    return stored(each, "members")


def all_pairs(sets: DataFrame) -> DataFrame:
    """As resemblance, with the pairs that share nothing at r = 0; counted where blocks of sets meet, so no pair is shuffled."""
    r = F.when(F.col("a") == 0, 0.0).otherwise(F.col("a") / (F.col("f_l") + F.col("f_r") - F.col("a")))
    return blocks.overlaps(members(sets)).withColumn("r", r)


def distance(pairs: DataFrame) -> DataFrame:
    return pairs.withColumn("d", 1 - F.col("r"))


def triangle_violations(sets: DataFrame) -> DataFrame:
    """Triples whose distances break the triangle inequality; none, as 1 - r is a metric."""
    p = all_pairs(sets)
    d = p.select("id_l", "id_r", (1 - F.col("r")).alias("d")).unionByName(p.select(F.col("id_r").alias("id_l"), F.col("id_l").alias("id_r"), (1 - F.col("r")).alias("d")))
    x, y, z = d.alias("x"), d.alias("y"), d.alias("z")
    j = x.join(y, F.col("x.id_r") == F.col("y.id_l")).join(z, (F.col("z.id_l") == F.col("x.id_l")) & (F.col("z.id_r") == F.col("y.id_r")))
    return j.where(F.col("z.d") > F.col("x.d") + F.col("y.d") + 1e-12).select(F.col("x.id_l").alias("a"), F.col("x.id_r").alias("b"), F.col("y.id_r").alias("c"))


def containment(small: DataFrame, large: DataFrame) -> DataFrame:
    """id_s, id_l, a, f_s, share: how much of each small set lies in each large one."""
    s, l = small.select(F.col("set_id").alias("id_s"), "elem"), large.select(F.col("set_id").alias("id_l"), "elem")
    f = sizes(small).select(F.col("set_id").alias("id_s"), F.col("f").alias("f_s"))
    a = s.join(l, "elem").groupBy("id_s", "id_l").agg(F.count("*").alias("a"))
    return a.join(f, "id_s").select("id_s", "id_l", "a", "f_s", (F.col("a") / F.col("f_s")).alias("share"))
