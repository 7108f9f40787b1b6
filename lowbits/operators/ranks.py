"""Minima of true permutations without sorting any: the least key of each set, then how many elements of the universe stand before it.

The rank of an element under a permutation is the number of elements with smaller keys, and signatures only need the ranks of
minima.  Two passes over the elements find them: neither keys nor ranks of the universe are sent or written, only k numbers for each
set and task, so this is for sets that are few next to their elements; see hashing.permutations for the ranks of a whole universe."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import Texts
from ..sources.io import stored

#: Rows hashed at a time, elements counted at a time, bytes of minima a task holds, minima of a counting task.
ROWS, ELEMENTS, TABLE_BYTES, MINIMA = 1 << 20, 1 << 16, 128 << 20, 1 << 22
#: Rows of a task of the first pass.
MOST_ROWS = 1 << 24


def signed(keys: np.ndarray) -> np.ndarray:
    """Unsigned keys as long, in the same order."""
    return (keys ^ np.uint64(1 << 63)).view(np.int64)


def lists(values: np.ndarray) -> pa.Array:
    """Rows of a matrix as a list column."""
    return pa.ListArray.from_arrays(pa.array(np.arange(len(values) + 1, dtype=np.int32) * values.shape[1]), pa.array(np.ascontiguousarray(values).reshape(-1)))


def runs(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.Table]:
    """Batches put together to so many rows or more."""
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held)


def minima(sets: DataFrame, k: int, seed: int = 0, universe: DataFrame | None = None, together: bool = False) -> DataFrame:
    """(set_id, f, z): ranks of each set's minima under k permutations of the universe (the sets' own elements by default), by the order of md5(seed:j:elem).

    together: rows of an element mostly lie side by side already, so they need not be brought together to be hashed once."""
    spark, kind = sets.sparkSession, sets.schema["set_id"].dataType.simpleString()
    cores = spark.sparkContext.defaultParallelism
    text = F.coalesce(F.col("elem").cast("string"), F.lit(""))
    elements = (sets if universe is None else universe).select("elem").distinct().select(text.alias("elem"))
    held = sets.where("elem is not null")
    if not together:
        held = held.repartition(max(2 * cores, math.ceil(held.count() / MOST_ROWS)), "elem").sortWithinPartitions("elem")
    id_type: list[pa.DataType] = []

    def least(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place: dict = {}
        f, table = np.zeros(0, np.int64), np.zeros((k, 0), np.int64)

        def flush() -> Iterator[pa.RecordBatch]:
            ids, step = pa.array(list(place), id_type[0]), max(1, (1 << 20) // k)
            for lo in range(0, len(ids), step):
                hi = min(lo + step, len(ids))
                yield pa.RecordBatch.from_arrays([ids[lo:hi], pa.array(f[lo:hi]), lists(table[:, lo:hi].T)], ["set_id", "f", "z"])

        for rows in runs(batches, ROWS):
            s, e = (rows.column(c).combine_chunks().dictionary_encode() for c in ("set_id", "elem"))
            id_type[:] = [s.dictionary.type]
            at = np.array([place.setdefault(x, len(place)) for x in s.dictionary.to_pylist()], np.int64)
            if len(place) > table.shape[1]:
                more = max(len(place), 2 * table.shape[1]) - table.shape[1]
                f, table = np.r_[f, np.zeros(more, np.int64)], np.concatenate((table, np.full((k, more), np.iinfo(np.int64).max)), axis=1)
            own, code = s.indices.to_numpy(), e.indices.to_numpy()
            order = np.argsort(own, kind="stable")
            code = code[order]
            first = np.flatnonzero(np.r_[True, np.diff(own[order]) != 0])
            at = at[own[order][first]]
            f[at] += np.diff(np.r_[first, len(own)])
            texts = Texts(e.dictionary.to_pylist())
            for j in range(k):
                table[j, at] = np.minimum(table[j, at], np.minimum.reduceat(signed(texts.keys(f"{seed}:{j}:"))[code], first))
            if table.nbytes > TABLE_BYTES:
                yield from flush()
                place, f, table = {}, np.zeros(0, np.int64), np.zeros((k, 0), np.int64)
        if place:
            yield from flush()

    parts = stored(held.select("set_id", text.alias("elem")).mapInArrow(least, f"set_id {kind}, f long, z array<long>"), "minima")
    width = math.ceil(k / min(k, 2 * cores))
    spans = math.ceil(k / width)
    shares = max(1, math.ceil(parts.select("set_id").distinct().count() * width / MINIMA))
    span = F.explode(F.sequence(F.lit(0), F.lit(spans - 1)))
    share = F.pmod(F.xxhash64("set_id"), F.lit(shares)).cast("int")
    sent = parts.select("set_id", "f", "z", share.alias("share"), span.alias("span"))
    sent = sent.select((F.col("share") * spans + F.col("span")).alias("task"), F.lit(False).alias("counts"), "set_id", "f", F.slice("z", F.col("span") * width + 1, F.lit(width)).alias("z"), F.lit(None).cast("string").alias("elem"))
    counted = elements.select(F.explode(F.sequence(F.lit(0), F.lit(spans * shares - 1))).alias("task"), F.lit(True).alias("counts"), F.lit(None).cast(sets.schema["set_id"].dataType).alias("set_id"), F.lit(None).cast("long").alias("f"), F.lit(None).cast("array<long>").alias("z"), "elem")
    dealt = sent.unionByName(counted).repartition(spans * shares, "task").sortWithinPartitions("task", "counts")

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: Places | None = None
        for batch in batches:
            t, c = batch.column(0).to_numpy(), batch.column(1).to_numpy(zero_copy_only=False)
            cut = [0, *(np.flatnonzero((np.diff(t) != 0) | (c[1:] != c[:-1])) + 1).tolist(), len(t)]
            for lo, hi in zip(cut, cut[1:]):
                if hi > lo:
                    if state is None or state.task != t[lo]:
                        if state is not None:
                            yield from state.ranks()
                        state = Places(int(t[lo]), int(t[lo]) % spans * width, seed)
                    (state.elements if c[lo] else state.least).append(batch.slice(lo, hi - lo))
                    if c[lo]:
                        state.count(ELEMENTS)
        if state is not None:
            yield from state.ranks()

    out = dealt.mapInArrow(places, f"set_id {kind}, f long, first int, ranks array<long>")
    z = F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("first", "ranks"))), lambda x: x["ranks"]))
    return out.groupBy("set_id").agg(F.max("f").alias("f"), z.alias("z"))


class Places:
    """Minima of some sets under some permutations, and how many elements stand before them."""

    def __init__(self, task: int, first: int, seed: int):
        self.task, self.first, self.seed = task, first, seed
        self.least: list[pa.RecordBatch] = []
        self.elements: list[pa.RecordBatch] = []
        self.z: np.ndarray | None = None

    def start(self) -> None:
        rows = pa.Table.from_batches(self.least)
        of_set = rows.column("set_id").combine_chunks().dictionary_encode()
        self.ids, own = of_set.dictionary, of_set.indices.to_numpy()
        values = rows.column("z").combine_chunks().flatten().to_numpy().reshape(len(own), -1)
        order = np.argsort(own, kind="stable")
        first = np.flatnonzero(np.r_[True, np.diff(own[order]) != 0])
        self.f = np.add.reduceat(rows.column("f").to_numpy()[order], first)
        z = np.minimum.reduceat(values[order], first, axis=0).T  # (permutations, sets)
        self.order = np.argsort(z, axis=1)
        self.z = np.take_along_axis(z, self.order, axis=1)
        self.before = np.zeros((z.shape[0], z.shape[1] + 1), np.int64)
        self.least = []

    def count(self, least: int) -> None:
        """Counts the elements that wait, once there are so many."""
        if not self.elements or sum(b.num_rows for b in self.elements) < least or not (self.least or self.z is not None):
            return
        if self.z is None:
            self.start()
        texts = Texts(pa.Table.from_batches(self.elements).column("elem").to_pylist())
        self.elements = []
        for j, z in enumerate(self.z):
            keys = signed(texts.keys(f"{self.seed}:{self.first + j}:"))
            keys = keys[keys < z[-1]]
            self.before[j] += np.bincount(np.searchsorted(z, keys, "right"), minlength=len(z) + 1)

    def ranks(self) -> Iterator[pa.RecordBatch]:
        self.count(1)
        if self.z is None:
            return
        out = np.empty_like(self.z)
        np.put_along_axis(out, self.order, np.cumsum(self.before, axis=1)[:, :-1], axis=1)
        step = max(1, (1 << 20) // len(out))
        for lo in range(0, len(self.ids), step):
            ids = self.ids[lo : lo + step]
            yield pa.RecordBatch.from_arrays([ids, pa.array(self.f[lo : lo + step]), pa.array([self.first] * len(ids), pa.int32()), lists(out[:, lo : lo + step].T)], ["set_id", "f", "first", "ranks"])
