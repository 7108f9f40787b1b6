"""All pairs of signatures, dealt to tasks as pairs of blocks of bounded size.

Every set belongs to a block by a hash of its id; a task holds two blocks at a time and compares them as arrays: words are
XORed, planes ORed, bits counted.  How many blocks there are follows from the number of sets and of tasks, never
from the session alone, so neither a broadcast nor a nested loop grows with the data; what is sent is the signatures
times the number of blocks.  Where blocks hold elements of many sets that is too much: then each block is stored as one
row, and the tasks read the two they compare.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import theory
from ..sources.io import remove, stored, written

LEAST_BLOCK, MOST_BLOCK = 256, 8192
MOST_MEMBERS = 1 << 22  # elements of a block's sets, where blocks hold them
ROWS_AT_ONCE = 1 << 18  # pairs whose words are held at a time
CELLS = 1 << 21  # pairs whose shared elements are counted at a time
MOST_PACKED = 1 << 15  # sets of a block that is one row
SLOTS = 1 << 16  # of the table that tells most elements that are not shared


class Side:
    """One block: ids, set sizes and planes, each (sets, words)."""

    def __init__(self, rows: pa.Table, planes: list[str]):
        self.ids = rows.column("set_id").combine_chunks()
        self.f = rows.column("f").to_numpy().astype(float)
        self.planes = [rows.column(c).combine_chunks().flatten().to_numpy().view(np.uint64).reshape(len(self.ids), -1) for c in planes]

    def __len__(self) -> int:
        return len(self.ids)


class Members(Side):
    """As Side, with the elements of the sets: elems[start[i] : start[i + 1]]."""

    def __init__(self, rows: pa.Table, planes: list[str]):
        super().__init__(rows, planes)
        elems = rows.column("elems").combine_chunks()
        self.start = np.r_[0, np.cumsum(pc.list_value_length(elems).to_numpy().astype(np.int64))]
        self.elems = elems.flatten()


class Shared:
    """How many elements the sets of two blocks share, by inverted lists of the right one; its cost is what they share."""

    def __init__(self, left: Members, right: Members):
        known = right.elems.dictionary_encode()
        code = known.indices.to_numpy()
        order = np.argsort(code, kind="stable")
        self.width = len(right)
        self.owner = np.repeat(np.arange(len(right), dtype=np.int32), np.diff(right.start))[order]
        self.size = np.bincount(code, minlength=len(known.dictionary))
        self.at = np.r_[0, np.cumsum(self.size)]
        mine = pc.fill_null(pc.index_in(left.elems, known.dictionary), -1).to_numpy()
        row = np.repeat(np.arange(len(left), dtype=np.int32), np.diff(left.start))
        self.row, self.code = row[mine >= 0], mine[mine >= 0]

    def counts(self, lo: int, hi: int) -> np.ndarray:
        """Matrix (rows lo..hi of left, right)."""
        first, last = np.searchsorted(self.row, (lo, hi))
        row, code = self.row[first:last].astype(np.int64) - lo, self.code[first:last]
        n = self.size[code]
        total = np.r_[0, np.cumsum(n)]
        out = np.zeros((hi - lo) * self.width, np.int64)
        a = 0
        while a < len(code):
            b = max(a + 1, int(np.searchsorted(total, total[a] + CELLS, "right")) - 1)
            m = n[a:b]
            other = self.owner[np.arange(total[b] - total[a]) + np.repeat(self.at[code[a:b]] - total[a:b] + total[a], m)]
            out += np.bincount(np.repeat(row[a:b] * self.width, m) + other, minlength=len(out))
            a = b
        return out.reshape(hi - lo, self.width)


def common(left: Members, right: Members, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """How many elements sets x of left and y of right share, pair by pair, x ascending; elements are integers and in order.  The cost is what the sets y hold."""
    out, table = np.zeros(len(x), np.int64), np.zeros(SLOTS, bool)
    if not len(x):
        return out
    of_left, of_right = left.elems.to_numpy(), right.elems.to_numpy()
    start, size = right.start[y], right.start[y + 1] - right.start[y]
    cut = np.r_[0, np.flatnonzero(np.diff(x)) + 1, len(x)]
    for lo, hi in zip(cut[:-1].tolist(), cut[1:].tolist()):
        own = of_left[left.start[x[lo]] : left.start[x[lo] + 1]]
        slots = own & (SLOTS - 1)
        table[slots] = True
        total = np.r_[0, np.cumsum(size[lo:hi])]
        other = of_right[np.arange(total[-1]) + np.repeat(start[lo:hi] - total[:-1], size[lo:hi])]
        hit = np.flatnonzero(table[other & (SLOTS - 1)])
        wanted = other[hit]
        hit = hit[own[np.minimum(np.searchsorted(own, wanted), len(own) - 1)] == wanted]
        out[lo:hi] = np.bincount(np.searchsorted(total, hit, "right") - 1, minlength=hi - lo)
        table[slots] = False
    return out


def packed(sig: DataFrame, rows: int, elements: int, tasks: int) -> DataFrame:
    """(no, data): sig (set_id, f, ...) in blocks of at most so many rows and elements, or of one row.  Stored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        no, held, n, size = TaskContext.get().partitionId() << 32, [], 0, 0

        def block() -> pa.RecordBatch:
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, held[0].schema) as out:
                out.write_table(pa.Table.from_batches(held).combine_chunks())
            return pa.RecordBatch.from_arrays([pa.array([no], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["no", "data"])

        for batch in batches:
            total, lo = np.r_[0, np.cumsum(batch.column(1).to_numpy())], 0
            while lo < batch.num_rows:
                hi = min(lo + rows - n, int(np.searchsorted(total, total[lo] + elements - size, "right")) - 1)
                if not held:
                    hi = max(hi, lo + 1)
                if hi > lo:
                    held.append(batch.slice(lo, hi - lo))
                    n, size, lo = n + hi - lo, size + total[hi] - total[lo], hi
                if lo < batch.num_rows:
                    yield block()
                    no, held, n, size = no + 1, [], 0, 0
        if held:
            yield block()

    return stored(sig.coalesce(tasks).mapInArrow(run, "no long, data binary"), "blocks")


def pairs_of_packed(sig: DataFrame, planes: list[str], fn: Callable[[Side, Side, bool], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """As pairs_of_blocks with members, but blocks are stored as one row each and read where they meet: nothing is sent, and what is stored is
    sig once, however many blocks there are."""
    spark = sig.sparkSession
    sig, path = written(sig.select("set_id", "f", *planes, "elems"), "signatures")
    n, total = sig.agg(F.count("*"), F.coalesce(F.sum("f"), F.lit(0))).first()
    wanted = min(math.ceil(math.sqrt(16 * spark.sparkContext.defaultParallelism)), math.ceil(n / LEAST_BLOCK))
    blocks = max(1, math.ceil(n / MOST_PACKED), math.ceil(total / MOST_MEMBERS), wanted)
    held = packed(sig, math.ceil(1.25 * n / blocks) or 1, math.ceil(1.25 * total / blocks), blocks)
    remove(spark, path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpacked = lambda x: Members(pa.ipc.open_stream(x.as_buffer()).read_all(), planes)
        last, left = None, None
        for batch in batches:
            for r in range(batch.num_rows):
                i, j = batch.column(0)[r].as_py(), batch.column(2)[r].as_py()
                if i != last:
                    last, left = i, unpacked(batch.column(1)[r])
                yield from fn(left, left, True) if i == j else fn(left, unpacked(batch.column(3)[r]), False)

    l, r = (held.select(F.col("no").alias(f"no_{s}"), F.col("data").alias(f"data_{s}")) for s in "lr")
    # rows are blocks; the hint keeps them from a broadcast
    return l.hint("shuffle_replicate_nl").join(r, F.col("no_l") <= F.col("no_r")).mapInArrow(run, schema)


def count_blocks(n: int, tasks: int) -> int:
    """As many blocks as give each task a pair of them, within the bounds of a block's size."""
    wanted = math.ceil(math.sqrt(2 * tasks))
    return max(1, math.ceil(n / MOST_BLOCK), min(wanted, math.ceil(n / LEAST_BLOCK)))


def pairs_of_blocks(sig: DataFrame, planes: list[str], fn: Callable[[Side, Side, bool], Iterator[pa.RecordBatch]], schema: str, blocks: int | None = None, members: bool = False, ratio: float | None = None) -> DataFrame:
    """fn(left, right, same) for every pair of blocks of sig (set_id, f, planes); same: both are one block, whose pairs count once.

    members: sig has elems, too, and both sides are Members.  These are sent once for each block, so there are only as many as cores or a
    block's bounds ask for.

    ratio: blocks are made of sets of like sizes, and only those meet that hold sizes of this ratio or over, the smaller one to the larger."""
    spark = sig.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)
    held, side = (["elems"], Members) if members else ([], Side)
    if members and not blocks:
        n, total = sig.agg(F.count("*"), F.coalesce(F.sum("f"), F.lit(0))).first()
        blocks = max(count_blocks(n, 2 * spark.sparkContext.defaultParallelism), math.ceil(total / MOST_MEMBERS))
    blocks = blocks or count_blocks(sig.count(), tasks)
    if ratio is not None:
        return met_by_size(sig, [*planes, *held], blocks, ratio, tasks).mapInArrow(dealer(planes, fn, side), schema)
    mine = F.pmod(F.xxhash64("set_id"), F.lit(blocks)).cast("int")
    dealt = sig.select("set_id", "f", *planes, *held, mine.alias("mine"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("other"))
    dealt = dealt.select(F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), (F.col("mine") > F.col("other")).alias("second"), "set_id", "f", *planes, *held)
    dealt = dealt.repartition(min(tasks, blocks * (blocks + 1) // 2), "i", "j").sortWithinPartitions("i", "j")
    return dealt.mapInArrow(dealer(planes, fn, side), schema)


def met_by_size(sig: DataFrame, columns: list[str], blocks: int, ratio: float, tasks: int) -> DataFrame:
    """sig dealt to the pairs of blocks whose sizes may have the ratio; blocks are ranges of sizes, the commonest sizes cut further by id."""
    spark = sig.sparkSession
    by_size = sig.groupBy("f").agg(F.count("*").alias("n")).orderBy("f").collect()  # as many rows as there are sizes
    most = max(1, math.ceil(sum(x.n for x in by_size) / blocks))
    ranges: list[list[int]] = []  # first and last size, sets
    for f, n in by_size:
        if ranges and ranges[-1][2] + n <= most:
            ranges[-1][1:] = [f, ranges[-1][2] + n]
        else:
            ranges.append([f, f, n])
    cuts, first = [math.ceil(n / most) for _, _, n in ranges], [0]
    for c in cuts:
        first.append(first[-1] + c)
    of_block = [x for x, c in enumerate(cuts) for _ in range(c)]
    meets = [(i, j) for i in range(len(of_block)) for j in range(len(of_block)) if ratio * max(ranges[of_block[i]][0], ranges[of_block[j]][0]) <= min(ranges[of_block[i]][1], ranges[of_block[j]][1]) * (1 + 1e-9)]
    sizes, last = [f for f, _ in by_size], 0
    table = []
    for x, (_, hi, _) in enumerate(ranges):
        while last < len(sizes) and sizes[last] <= hi:
            table.append((sizes[last], first[x], cuts[x]))
            last += 1
    size = spark.createDataFrame(table, "f long, start int, cuts int")
    both = spark.createDataFrame(meets, "mine int, other int")
    own = sig.select("set_id", "f", *columns).join(F.broadcast(size), "f")
    own = own.withColumn("mine", (F.col("start") + F.pmod(F.xxhash64("set_id"), F.col("cuts"))).cast("int")).join(F.broadcast(both), "mine")
    own = own.select(F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), (F.col("mine") > F.col("other")).alias("second"), "set_id", "f", *columns)
    return own.repartition(max(1, min(tasks, len(meets))), "i", "j").sortWithinPartitions("i", "j")


def dealer(planes: list[str], fn: Callable, side: type) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """fn over the pairs of blocks (i, j, second, ...) that lie side by side."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, batches_of = None, []

        def flush() -> Iterator[pa.RecordBatch]:
            rows = pa.Table.from_batches(batches_of)
            second = rows.column("second").to_numpy()
            left = side(rows.filter(pa.array(~second)), planes)
            if key[0] == key[1]:
                yield from fn(left, left, True)
            elif second.any() and len(left):
                yield from fn(left, side(rows.filter(pa.array(second)), planes), False)

        for batch in batches:
            i, j = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            cut = [0, *(np.flatnonzero((np.diff(i) != 0) | (np.diff(j) != 0)) + 1).tolist(), len(i)]
            for a, b in zip(cut, cut[1:]):
                if b > a:
                    if batches_of and key != (i[a], j[a]):
                        yield from flush()
                        batches_of = []
                    key = (i[a], j[a])
                    batches_of.append(batch.slice(a, b - a))
        if batches_of:
            yield from flush()

    return run


def residues(f: np.ndarray, domain: float, b: int) -> np.ndarray:
    """theory.residue of sets of f elements."""
    return np.array([theory.residue(x / domain, b) for x in np.unique(f)])[np.unique(f, return_inverse=True)[1]]


def floors_slopes(f1: np.ndarray, f2: np.ndarray, domain: float, b: int) -> tuple[np.ndarray, np.ndarray]:
    """Matrices (sets of f1, sets of f2) of floor and slope of the match law."""
    q1, q2 = residues(f1, domain, b)[:, None], residues(f2, domain, b)[None, :]
    total = f1[:, None] + f2[None, :]
    s1, s2 = f1[:, None] / total, f2[None, :] / total
    return q1 * s2 + q2 * s1, 1 - (q1 * s1 + q2 * s2)


def differing(left: Side, right: Side, lo: int, hi: int, bs: list[int]) -> Iterator[tuple[int, np.ndarray]]:
    """(b, counts) for each b, ascending: counts[w, x, y] are the samples of word w whose lowest b bits differ."""
    word, done = None, 0
    for b in sorted(bs):
        for i in range(done, b):
            x = left.planes[i][lo:hi].T[:, :, None] ^ right.planes[i].T[:, None, :]
            word = x if word is None else np.bitwise_or(word, x, out=word)
        done = b
        yield b, np.bitwise_count(word)


def first_samples(left: Side, right: Side, lo: int, hi: int, b: int, k: int) -> np.ndarray:
    """Samples among the first k, within the last word they reach into, whose lowest b bits differ."""
    w, mask = k // 64, np.uint64((1 << (k % 64)) - 1)
    word = None
    for i in range(b):
        x = left.planes[i][lo:hi, w][:, None] ^ right.planes[i][:, w][None, :]
        word = x if word is None else word | x
    return np.bitwise_count(word & mask)


def mismatch_counts(left: Side, right: Side, lo: int, hi: int, ks: list[int], bs: list[int]) -> Iterator[tuple[int, int, np.ndarray]]:
    """(b, k, mismatches) as matrices over rows lo..hi of left, for every b and k."""
    for b, counts in differing(left, right, lo, hi, bs):
        for k in sorted(ks):
            m = counts[0] if k == 64 else counts[: k // 64].sum(axis=0, dtype=np.int32)
            yield b, k, m + first_samples(left, right, lo, hi, b, k) if k % 64 else m


def _chunks(left: Side, right: Side) -> Iterator[tuple[int, int]]:
    words = max(1, left.planes[0].shape[1])
    step = max(1, ROWS_AT_ONCE // max(1, len(right) * words))
    for lo in range(0, len(left), step):
        yield lo, min(lo + step, len(left))


def places(left: Side, right: Side) -> tuple[pa.Array, np.ndarray]:
    """(ids of both sides in a row, their order)."""
    ids = pa.concat_arrays([left.ids, right.ids])
    rank = np.empty(len(ids), np.int64)
    rank[pc.sort_indices(ids).to_numpy()] = np.arange(len(ids))
    return ids, rank


def every_pair(lo: int, hi: int, width: int, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """(x, y) of all pairs of rows lo..hi of left, counted from lo, and of right."""
    if same:
        return np.nonzero(np.arange(lo, hi)[:, None] < np.arange(width)[None, :])
    return np.repeat(np.arange(hi - lo), width), np.tile(np.arange(width), hi - lo)


def overlaps(sets: DataFrame) -> DataFrame:
    """id_l < id_r, f_l, f_r, a of all pairs of sets (set_id, f, elems), those that share nothing too, counted where blocks of sets meet: no pair is shuffled."""
    kind = sets.schema["set_id"].dataType.simpleString()

    def run(left: Members, right: Members, same: bool) -> Iterator[pa.RecordBatch]:
        ids, rank = places(left, right)
        f, both = np.concatenate((left.f, right.f)).astype(np.int64), Shared(left, right)
        step = max(1, ROWS_AT_ONCE // len(right))
        many = step * max(1, CELLS // (len(right) * step))
        for top in range(0, len(left), many):
            end = min(len(left), top + many)
            a = both.counts(top, end)
            for lo in range(top, end, step):
                hi = min(lo + step, end)
                x, y = every_pair(lo, hi, len(right), same)
                if len(x):
                    l, r = ordered(rank, x + lo, y + len(left))
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(l)), ids.take(pa.array(r)), pa.array(f[l]), pa.array(f[r]), pa.array(a[x + lo - top, y])], ["id_l", "id_r", "f_l", "f_r", "a"])

    return pairs_of_blocks(sets, [], run, f"id_l {kind}, id_r {kind}, f_l long, f_r long, a long", members=True)


def equal_samples(sig: DataFrame, k: int) -> DataFrame:
    """id_l < id_r, equal: bit j is set where the j-th of k <= 64 minima (set_id, f, z) are the same; every pair."""
    kind = sig.schema["set_id"].dataType.simpleString()

    def run(left: Side, right: Side, same: bool) -> Iterator[pa.RecordBatch]:
        ids, rank = places(left, right)
        (mine,), (other,) = left.planes, right.planes
        step = max(1, ROWS_AT_ONCE // len(right))
        for lo in range(0, len(left), step):
            hi = min(lo + step, len(left))
            equal = np.zeros((hi - lo, len(right)), np.uint64)
            for j in range(k):
                equal |= (mine[lo:hi, j][:, None] == other[:, j][None, :]).astype(np.uint64) << np.uint64(j)
            x, y = every_pair(lo, hi, len(right), same)
            if len(x):
                l, r = ordered(rank, x + lo, y + len(left))
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(l)), ids.take(pa.array(r)), pa.array(equal[x, y].view(np.int64))], ["id_l", "id_r", "equal"])

    return pairs_of_blocks(sig, ["z"], run, f"id_l {kind}, id_r {kind}, equal long")


def half_up(x: np.ndarray, digits: int = 6) -> np.ndarray:
    """Rounded, halves away from zero."""
    y = x * 10.0**digits
    whole = np.trunc(y)
    return np.where(np.abs(y - whole) == 0.5, whole + np.sign(y), np.rint(y)) / 10.0**digits


def estimates(sig: DataFrame, k: int, b: int, r0: float, domain: float, digits: int = 6, many: bool = False) -> DataFrame:
    """Pairs whose low-bit estimate reaches r0 next to their exact resemblance, rounded; sig: set_id, f, elems and planes.

    Both are counted where blocks of sets meet.  For thresholds that a large part of all pairs reaches, as no pair is shuffled or written.

    many: sets are so many that blocks are read where they meet (pairs_of_packed), and shared elements, which are integers and in order, are
    counted for what reaches r0 alone."""
    kind = sig.schema["set_id"].dataType.simpleString()

    def run(left: Members, right: Members, same: bool) -> Iterator[pa.RecordBatch]:
        ids, rank = places(left, right)
        f, both = np.concatenate((left.f, right.f)), None if many else Shared(left, right)
        q, most = residues(f, domain, b), most_mismatches(left, right, k, b, r0, domain)
        step = max(1, ROWS_AT_ONCE // len(right))
        at_once = step * max(1, CELLS // (len(right) * step))
        for top in range(0, len(left), at_once):
            end = min(len(left), top + at_once)
            shared = None if many else both.counts(top, end)
            for lo in range(top, end, step):
                hi = min(lo + step, end)
                ((_, _, m),) = mismatch_counts(left, right, lo, hi, [k], [b])
                x, y = np.nonzero(m <= most)
                if same:
                    once = x + lo < y
                    x, y = x[once], y[once]
                matches, f1, f2, q1, q2 = k - m[x, y].astype(np.int64), left.f[lo:hi][x], right.f[y], q[lo:hi][x], q[len(left) :][y]
                e, total = matches / k, f1 + f2
                slope = 1 - (q1 * f1 + q2 * f2) / total
                r = (e - (q1 * f2 + q2 * f1) / total) / slope
                near = r >= r0
                x, y, matches, e, r, slope, total = x[near], y[near], matches[near], e[near], r[near], slope[near], total[near]
                if len(x):
                    i, j = ordered(rank, x + lo, y + len(left))
                    a = common(left, right, x + lo, y) if many else shared[x + lo - top, y]
                    rounded = [pa.array(half_up(v, digits)) for v in (e, r, a / (total - a), np.sqrt(e * (1 - e) / k) / slope)]
                    yield pa.RecordBatch.from_arrays([ids.take(pa.array(i)), ids.take(pa.array(j)), *(pa.array(f[p].astype(np.int64)) for p in (i, j)), pa.array(matches), *rounded], ["id_l", "id_r", "f_l", "f_r", "matches", "e_hat", "r_hat", "r_exact", "std_err"])

    out = f"id_l {kind}, id_r {kind}, f_l long, f_r long, matches long, e_hat double, r_hat double, r_exact double, std_err double"
    names = [f"plane_{i}" for i in range(b)]
    return pairs_of_packed(sig, names, run, out) if many else pairs_of_blocks(sig, names, run, out, members=True)


def ordered(rank: np.ndarray, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places x and y of pairs, the smaller id first."""
    swap = rank[x] > rank[y]
    return np.where(swap, y, x), np.where(swap, x, y)


def most_mismatches(left: Side, right: Side, k: int, b: int, r0: float | None, domain: float | None) -> int:
    """No pair of the two blocks with more mismatches reaches r0: an integer test, so that only what passes it is estimated.

    Floor and slope are weighted means of residues and of one less residues, so they lie between the least and greatest of both blocks."""
    if r0 is None:
        return k
    least = t = r0 - 1e-9
    if domain is not None:
        q = residues(np.unique(np.concatenate((left.f, right.f))), domain, b)
        least = q.min() + (1 - (q.max() if t > 0 else q.min())) * t
    return min(k, math.floor(k * (1 - least) + 1e-6))


def compare(sig: DataFrame, k: int, b: int, r0: float | None = None, domain: float | None = None, plane: str = "plane_{}", blocks: int | None = None, ratio: float | None = None) -> DataFrame:
    """id_l < id_r, f_l, f_r, mismatches of all pairs; with r0, of those whose estimate reaches it.

    ratio: only pairs whose sizes have this ratio or over, the smaller one to the larger.

    domain: the range that densities of low-bit estimates refer to; none: plain shares of equal samples."""
    kind = sig.schema["set_id"].dataType.simpleString()
    planes = [plane.format(i) for i in range(b)]

    def run(left: Side, right: Side, same: bool) -> Iterator[pa.RecordBatch]:
        ids, rank = places(left, right)
        q = residues(np.concatenate((left.f, right.f)), domain, b) if domain is not None else None
        most = most_mismatches(left, right, k, b, r0, domain)
        for lo, hi in _chunks(left, right):
            ((_, _, m),) = mismatch_counts(left, right, lo, hi, [k], [b])
            x, y = np.nonzero(m <= most)
            if same:
                once = x + lo < y
                x, y = x[once], y[once]
            if ratio is not None:
                f1, f2 = left.f[lo:hi][x], right.f[y]
                fits = (f1 >= ratio * f2) & (f2 >= ratio * f1)
                x, y = x[fits], y[fits]
            if r0 is not None:
                share = (k - m[x, y].astype(np.int64)) / k
                if domain is not None:
                    q1, q2, f1, f2 = q[lo:hi][x], q[len(left) :][y], left.f[lo:hi][x], right.f[y]
                    s1, s2 = f1 / (f1 + f2), f2 / (f1 + f2)
                    share = (share - (q1 * s2 + q2 * s1)) / (1 - (q1 * s1 + q2 * s2))
                near = share >= r0 - 1e-9
                x, y = x[near], y[near]
            if not len(x):
                continue
            l, r = ordered(rank, x + lo, y + len(left))
            f = np.concatenate((left.f, right.f)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(l)), ids.take(pa.array(r)), pa.array(f[l]), pa.array(f[r]), pa.array(m[x, y].astype(np.int64))], ["id_l", "id_r", "f_l", "f_r", "mismatches"])

    return pairs_of_blocks(sig, planes, run, f"id_l {kind}, id_r {kind}, f_l long, f_r long, mismatches long", blocks, ratio=ratio)


def retrieved(sig: DataFrame, ks: list[int], bs: list[int], full_bits: int, domain: float, thresholds: list[float], blocks: int | None = None) -> DataFrame:
    """estimator, b, k, r0, n_ret: how many of all pairs each estimate puts at r0 or over; each task sends counts only."""

    def run(left: Side, right: Side, same: bool) -> Iterator[pa.RecordBatch]:
        total: dict[tuple, int] = {}
        for lo, hi in _chunks(left, right):
            once = np.arange(lo, hi)[:, None] < np.arange(len(right))[None, :] if same else None
            laws = {b: floors_slopes(left.f[lo:hi], right.f, domain, b) for b in bs}
            for b, k, m in mismatch_counts(left, right, lo, hi, ks, [*bs, full_bits]):
                share = (k - m) / k
                if b in laws:
                    share = (share - laws[b][0]) / laws[b][1]
                if once is not None:
                    share = share[once]
                for t in thresholds:
                    total[(b, k, t)] = total.get((b, k, t), 0) + int(np.count_nonzero(share >= t))
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(["full" if b == full_bits else "low" for b, _, _ in total]), pa.array([32 if b == full_bits else b for b, _, _ in total], pa.int32()), pa.array([k for _, k, _ in total], pa.int32()), pa.array([t for _, _, t in total], pa.float64()), pa.array(list(total.values()), pa.int64())], ["estimator", "b", "k", "r0", "n_ret"])

    counted = pairs_of_blocks(sig, [f"plane_{i}" for i in range(full_bits)], run, "estimator string, b int, k int, r0 double, n_ret long", blocks)
    return counted.groupBy("estimator", "b", "k", "r0").agg(F.sum("n_ret").alias("n_ret"))


def hits(pairs: DataFrame, ks: list[int], bs: list[int], full_bits: int, domain: float, thresholds: list[float]) -> DataFrame:
    """estimator, b, k, r0, n_rel, n_hit of given pairs: r, f_l, f_r and the planes of both sides as l_{i}, r_{i}; a batch sends counts only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple, np.ndarray] = {}
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            r, f1, f2 = (batch.column(c).to_numpy().astype(float) for c in ("r", "f_l", "f_r"))
            words = lambda c: batch.column(c).flatten().to_numpy().view(np.uint64).reshape(n, -1)
            apart, done = None, 0
            for b in sorted([*bs, full_bits]):
                for i in range(done, b):
                    x = words(f"l_{i}") ^ words(f"r_{i}")
                    apart = x if apart is None else apart | x
                done = b
                if b != full_bits:
                    q1, q2 = residues(f1, domain, b), residues(f2, domain, b)
                    s1, s2 = f1 / (f1 + f2), f2 / (f1 + f2)
                    floor, slope = q1 * s2 + q2 * s1, 1 - (q1 * s1 + q2 * s2)
                for k in ks:
                    w = apart[:, : -(-k // 64)].copy()
                    if k % 64:
                        w[:, -1] &= np.uint64((1 << (k % 64)) - 1)
                    share = (k - np.bitwise_count(w).sum(axis=1, dtype=np.int64)) / k
                    if b != full_bits:
                        share = (share - floor) / slope
                    for t in thresholds:
                        relevant = r >= t
                        total[(b, k, t)] = total.get((b, k, t), np.zeros(2, np.int64)) + (np.count_nonzero(relevant), np.count_nonzero(relevant & (share >= t)))
        if total:
            yield pa.RecordBatch.from_arrays([pa.array(["full" if b == full_bits else "low" for b, _, _ in total]), pa.array([32 if b == full_bits else b for b, _, _ in total], pa.int32()), pa.array([k for _, k, _ in total], pa.int32()), pa.array([t for _, _, t in total], pa.float64()), *(pa.array([int(x[c]) for x in total.values()], pa.int64()) for c in (0, 1))], ["estimator", "b", "k", "r0", "n_rel", "n_hit"])

    counted = pairs.mapInArrow(run, "estimator string, b int, k int, r0 double, n_rel long, n_hit long")
    return counted.groupBy("estimator", "b", "k", "r0").agg(F.sum("n_rel").alias("n_rel"), F.sum("n_hit").alias("n_hit"))
