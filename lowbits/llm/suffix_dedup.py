"""Suffix-array dedup of byte strings: blockwise construction with a difference cover (operator 5).

A byte goes if a string of ``LENGTH`` bytes that covers it also starts anywhere else, in the same document or another.
Only suffixes that start such a string matter, and only their first LENGTH bytes, so suffixes are sorted to that depth.

1. Buckets.  Each suffix belongs to the least-hashed k-gram among its first LENGTH bytes, its anchor: equal strings have equal
   anchors at equal offsets, so equal suffixes share a bucket.  Runs of suffixes with one anchor are one row: a digest
   of the bytes the run spans.  Runs with equal digests repeat as a whole.  Buckets with one run are done.
2. Sort.  Of a bucket with different runs, one run of each kind is fetched.  A task takes the buckets it
   is dealt one at a time: suffixes are split by their first and last bytes, and long ties are resolved
   by ranks of a difference-cover sample: for any two positions there is a shift under the cover's period that
   takes both to sampled positions, whose ranks were computed before.  Memory is bounded by one bucket's runs.
   Buckets of more than ``BUCKET`` different runs are spread instead, by digests of the strings themselves.
3. Removed runs are joined per document, and the bytes left are hashed.

Beside the bytes that go, ``shared_passages`` says which documents share a passage of words with another document, however
few bytes it has: of every ``PASSAGE`` consecutive words the least-hashed string of ``STRING`` of them is an anchor, so documents
that share a passage have an anchor in common, and documents with a common anchor share STRING words.

Edge cases: null and empty texts are zero bytes; texts shorter than LENGTH lose nothing; matches never cross
documents.  Repeated rows repeat each other and lose all strings of that length.  Rows are identified by
doc_id and a text hash, so a null or shared doc_id does no harm.  An empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytewords import U64, _powers, byte_table, mix, ngram_hashes, text_slices, word_hashes, words
from .engine import lean, map_batches, partitions, same_row, stored
from .line_dedup import _packed, _part

LENGTH, GRAM, PERIOD, BUCKET = 400, 64, 32, 4096
PASSAGE, STRING = 51, 34
#: Separators: space and the control characters 9 to 13; letters keep their case.
EXACT_WORDS = byte_table(bytes([32, *range(9, 14)]), False)


@lru_cache
def difference_cover(period: int) -> list[int]:
    """A small set of residues whose differences give every residue (greedy)."""
    cover, have = [0, 1], {0, 1, period - 1}
    while len(have) < period:
        gains = {c: {(c - x) % period for x in cover} | {(x - c) % period for x in cover} for c in range(period) if c not in cover}
        best = max(gains, key=lambda c: (len(gains[c] - have), -c))
        cover.append(best)
        have |= gains[best]
    return sorted(cover)


@lru_cache
def cover_shifts(period: int) -> np.ndarray:
    """shift[i, j]: the least d with i + d and j + d both in the difference cover of the period."""
    cover = difference_cover(period)
    inside = np.zeros(period, bool)
    inside[cover] = True
    d = np.arange(period)
    both = inside[(d[:, None, None] + d) % period] & inside[(d[None, :, None] + d) % period]
    return both.argmax(axis=2)


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each run of w values (len(x) - w + 1 of them), by prefix and suffix minima of blocks."""
    n = len(x) - w + 1
    size = -(-len(x) // w) * w
    y = np.full(size, np.iinfo(np.uint64).max, np.uint64)
    y[: len(x)] = x
    y = y.reshape(-1, w)
    ahead = np.minimum.accumulate(y, axis=1).ravel()
    back = np.minimum.accumulate(y[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[w - 1 : w - 1 + n])


def rolling(buf: np.ndarray, length: int) -> np.ndarray:
    """A 64-bit hash of every run of length bytes."""
    n = len(buf) - length + 1
    if n <= 0:
        return np.zeros(0, U64)
    p, q = _powers(len(buf) + 1)
    total = np.zeros(len(buf) + 1, U64)
    np.cumsum((buf.astype(U64) + U64(1)) * p[: len(buf)], out=total[1:], dtype=U64)
    return mix((total[length:] - total[:-length]) * q[:n])


def runs(buf: np.ndarray, off: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """(document, first suffix, number of suffixes, anchor position, anchor hash) of the runs of suffixes with one anchor."""
    empty = np.zeros(0, np.int64)
    if len(buf) < length:
        return empty, empty, empty, empty, np.zeros(0, U64)
    h = rolling(buf, gram)
    low = sliding_min((h & ~U64(0xFFFFFFFF)) | np.arange(len(h), dtype=U64), length - gram + 1)
    at = (low & U64(0xFFFFFFFF)).astype(np.int64)
    end = np.repeat(off[1:], np.diff(off))[: len(at)]
    ok = np.arange(len(at)) + length <= end
    i = np.flatnonzero(ok)
    if not len(i):
        return empty, empty, empty, empty, np.zeros(0, U64)
    a = at[i]
    new = np.concatenate(([True], (a[1:] != a[:-1]) | (i[1:] != i[:-1] + 1)))
    first = np.flatnonzero(new)
    many = np.diff(np.append(first, len(i)))
    s, a = i[first], a[first]
    return np.searchsorted(off[1:], s, side="right"), s, many, a, h[a]


ROW = "kind int, doc_id long, th long, n_bytes long, sha string, start int, many int, anchor long, c1 long, c2 long"


def _scan(length: int, gram: int):
    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        ids, th = batch.column(0), batch.column(1)
        for lo, hi, buf, off in text_slices(batch, "text"):
            raw, ends = buf.tobytes(), off.tolist()
            size = hi - lo
            null = lambda t, n: pa.nulls(n, t)
            sha = [hashlib.sha256(raw[a:b]).hexdigest() for a, b in zip(ends, ends[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(size, np.int32)), ids.slice(lo, size), th.slice(lo, size), pa.array(np.diff(off)), pa.array(sha), *(null(pa.int32(), size) for _ in range(2)), *(null(pa.int64(), size) for _ in range(3))], [x.split()[0] for x in ROW.split(", ")])
            d, s, many, a, h = runs(buf, off, length, gram)
            n = len(d)
            if not n:
                continue
            lead = a - s
            digest = b"".join(hashlib.blake2b(raw[x : x + m + length - 1], digest_size=16, salt=m.to_bytes(8, "little") + g.to_bytes(8, "little")).digest() for x, m, g in zip(s.tolist(), many.tolist(), lead.tolist()))
            c = np.frombuffer(digest, "<i8").reshape(-1, 2)
            where = pa.array(d + lo)
            yield pa.RecordBatch.from_arrays([pa.array(np.ones(n, np.int32)), ids.take(where), th.take(where), null(pa.int64(), n), null(pa.string(), n), pa.array((s - off[d]).astype(np.int32)), pa.array(many.astype(np.int32)), pa.array(h.view(np.int64)), pa.array(np.ascontiguousarray(c[:, 0])), pa.array(np.ascontiguousarray(c[:, 1]))], [x.split()[0] for x in ROW.split(", ")])

    return run


def repeated_starts(texts: list[bytes], counts: list[int], length: int, period: int = PERIOD) -> list[np.ndarray]:
    """For each text, which of its first counts[t] suffixes agree with another one on their first length bytes.

    All suffixes are one bucket.  Ties of the first and last ``period`` bytes are resolved by cover ranks."""
    cover = difference_cover(period)
    shift = cover_shifts(period)
    buf = np.frombuffer(b"".join(texts), np.uint8)
    off = np.concatenate(([0], np.cumsum([len(t) for t in texts]))).astype(np.int64)
    counts = np.asarray(counts)
    pos = np.repeat(off[:-1], counts) + np.arange(int(counts.sum())) - np.repeat(np.cumsum(counts) - counts, counts)
    # ranks of sampled positions by the bytes that any shift leaves to compare
    depth = length - period + 1
    rank = np.zeros(len(buf), np.int64)
    sample = rolling(buf, depth)
    inside = np.zeros(period, bool)
    inside[cover] = True
    at = np.flatnonzero(inside[np.arange(len(sample)) % period])
    rank[at] = np.unique(sample[at], return_inverse=True)[1]
    head = rolling(buf, period)
    group = np.unique(head[pos] + U64(0x9E3779B97F4A7C15) * head[pos + length - period], return_inverse=True)[1]
    repeated = np.zeros(len(pos), bool)
    todo = np.argsort(group, kind="stable")
    while len(todo):
        g = group[todo]
        new = np.concatenate(([True], g[1:] != g[:-1]))
        first = np.flatnonzero(new)
        size = np.diff(np.append(first, len(todo)))
        pivot = np.repeat(todo[first], size)
        i, j = pos[todo], pos[pivot]
        d = shift[i % period, j % period]
        same = (rank[i + d] == rank[j + d]) & (todo != pivot)
        k = np.flatnonzero(same)
        for lo in range(0, len(k), 1 << 16):  # the strings themselves decide
            part = k[lo : lo + (1 << 16)]
            x, y = i[part], j[part]
            equal = np.ones(len(part), bool)
            for b in range(0, length, 50):
                step = np.arange(b, min(b + 50, length))
                equal &= (buf[x[:, None] + step] == buf[y[:, None] + step]).all(axis=1)
            same[part[~equal]] = False
        repeated[todo[same]] = True
        repeated[pivot[same]] = True
        todo = todo[~same & (todo != pivot) & np.repeat(size > 1, size)]
    return np.split(repeated, np.cumsum(counts)[:-1])


def _ranges(mask: np.ndarray, start: int) -> list[tuple[int, int]]:
    edge = np.flatnonzero(np.diff(np.concatenate(([0], mask.astype(np.int8), [0]))))
    return [(start + int(a), int(b - a)) for a, b in zip(edge[::2], edge[1::2])]


_SPAN = "doc_id long, th long, start int, many int"


def _span_rows(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) or [[]] * 4
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int32(), pa.int32()))], ["doc_id", "th", "start", "many"])


def _sort_buckets(length: int):
    """Takes all rows (anchor, doc_id, th, start, many, open, bytes) of a partition, one bucket after the other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bucket, held = None, []

        def flush() -> Iterator[pa.RecordBatch]:
            marks = repeated_starts([x[5] for x in held], [x[3] for x in held], length)
            rows = [(x[0], x[1], *r) for x, m in zip(held, marks) if x[4] for r in _ranges(m, x[2])]
            if rows:
                yield _span_rows(rows)

        for batch in batches:
            for anchor, *x in zip(*(c.to_pylist() for c in batch.columns)):
                if anchor != bucket:
                    if len(held) > 1:
                        yield from flush()
                    bucket, held = anchor, []
                held.append(x)
        if len(held) > 1:
            yield from flush()

    return run


def repeated_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, bucket: int = BUCKET) -> tuple[DataFrame, DataFrame]:
    """(documents: doc_id, th, n_bytes, sha; repeated: doc_id, th, text and spans of suffix starts, for documents that lose bytes or might)."""
    spark = docs.sparkSession
    parts = partitions(spark, docs)
    docs = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), docs["text"].alias("text"))
    state = stored(map_batches(docs, _scan(length, gram), ROW), "runs")
    base = state.where("kind = 0").select("doc_id", "th", "n_bytes", "sha")
    every = state.where("kind = 1").select("doc_id", "th", "start", "many", "anchor", "c1", "c2")
    # stored, so that the join has nothing to do but join and Spark can split an anchor that a third of all rows have
    met = stored(every.groupBy("anchor").agg(F.count("*").alias("n")).where("n > 1").select("anchor"), "anchors")
    found = stored(every.join(met, "anchor", "left_semi"), "met")  # most buckets hold one run and end here
    kinds = stored(found.groupBy("anchor", "c1", "c2").agg(F.count("*").alias("copies"), F.min(F.struct("doc_id", "th", "start", "many")).alias("one")), "kinds")
    buckets = stored(kinds.groupBy("anchor").agg(F.count("*").alias("kinds")).where("kinds > 1"), "buckets")
    whole = kinds.where("copies > 1").select(F.col("c1").alias("x1"), F.col("c2").alias("x2"))
    full = found.join(whole, (F.col("c1") == F.col("x1")) & (F.col("c2") == F.col("x2"))).select("doc_id", "th", "start", "many", F.lit(None).cast("long").alias("anchor"), F.lit(0).alias("role"))
    # role 1: a run that others may share in part; role 2: one of several equal runs, done but a partner
    partial = kinds.join(buckets, "anchor").select("one.doc_id", "one.th", "one.start", "one.many", "anchor", F.when(F.col("kinds") > bucket, F.lit(3)).otherwise(F.lit(1)).alias("role"), "copies")
    partial = partial.select("doc_id", "th", "start", "many", "anchor", F.when((F.col("role") == 1) & (F.col("copies") > 1), F.lit(2)).otherwise(F.col("role")).alias("role"))
    wanted = full.unionByName(partial).groupBy("doc_id", "th").agg(F.collect_list(F.struct("start", "many", "anchor", "role")).alias("runs"))  # of one document
    wanted = wanted.select(F.col("doc_id").alias("d"), F.col("th").alias("t"), "runs")
    near = stored(docs.join(wanted, same_row()).select("doc_id", "th", "text", "runs"), "near")

    def fetch(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for lo in range(0, batch.num_rows, 256):
            part = batch.slice(lo, 256)
            out = []
            for d, t, x, rs in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), part.column(2).cast(pa.binary()).to_pylist(), part.column(3).to_pylist()):
                out += [(r["anchor"], d, t, r["start"], r["many"], r["role"] == 1, r["role"] == 3, x[r["start"] : r["start"] + r["many"] + length - 1]) for r in rs if r["role"]]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.bool_(), pa.bool_(), pa.binary()))], ["anchor", "doc_id", "th", "start", "many", "open", "wide", "bytes"])

    pieces = map_batches(near.select("doc_id", "th", "text", "runs"), fetch, "anchor long, doc_id long, th long, start int, many int, open boolean, wide boolean, bytes binary")
    dealt = pieces.where("not wide").drop("wide").repartition(parts, "anchor").sortWithinPartitions("anchor")
    spans = dealt.mapInArrow(lean(_sort_buckets(length)), _SPAN)
    if not buckets.where(F.col("kinds") > bucket).isEmpty():

        def strings(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for d, t, s, m, x in zip(*(batch.column(k).to_pylist() for k in (1, 2, 3, 4, 7))):
                digest = b"".join(hashlib.blake2b(x[i : i + length], digest_size=16).digest() for i in range(m))
                c = np.frombuffer(digest, "<i8").reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array([d] * m, pa.int64()), pa.array([t] * m, pa.int64()), pa.array(np.arange(s, s + m, dtype=np.int32)), pa.array(np.ascontiguousarray(c[:, 0])), pa.array(np.ascontiguousarray(c[:, 1]))], ["doc_id", "th", "start", "c1", "c2"])

        each = map_batches(pieces.where("wide"), strings, "doc_id long, th long, start int, c1 long, c2 long")
        twice = each.groupBy("c1", "c2").agg(F.count("*").alias("n")).where("n > 1")
        spans = spans.unionByName(each.join(twice, ["c1", "c2"]).select("doc_id", "th", "start", F.lit(1).alias("many")))
    own = near.select("doc_id", "th", F.explode("runs").alias("r")).where("r.role = 0").select("doc_id", "th", "r.start", "r.many")
    spans = spans.unionByName(own).groupBy("doc_id", "th").agg(F.collect_list(F.struct("start", "many")).alias("spans"))  # of one document
    spans = spans.select(F.col("doc_id").alias("d"), F.col("th").alias("t"), "spans")
    repeated = near.join(spans, same_row()).select("doc_id", "th", "text", "spans")
    return base, repeated


CUT = "doc_id long, th long, n_removed long, removed array<struct<start:int,end:int>>, kept_sha256 string, kept binary"


def cut(repeated: DataFrame, length: int = LENGTH) -> DataFrame:
    """n_removed, removed (byte offsets), kept_sha256 and kept of documents with spans of suffix starts."""
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for lo in range(0, batch.num_rows, 256):
            part = batch.slice(lo, 256)
            out = []
            for x, ss in zip(part.column(2).cast(pa.binary()).to_pylist(), part.column(3).to_pylist()):
                mark = np.zeros(len(x) + 1, np.int32)
                for s in ss:
                    mark[s["start"]] += 1
                    mark[s["start"] + s["many"] + length - 1] -= 1
                edge = np.flatnonzero(np.diff(np.concatenate(([0], (np.cumsum(mark[:-1]) > 0).astype(np.int8), [0])))).tolist()
                kept = b"".join(x[a:b] for a, b in zip([0, *edge[1::2]], [*edge[::2], len(x)]))
                out.append((len(x) - len(kept), [{"start": a, "end": b} for a, b in zip(edge[::2], edge[1::2])], hashlib.sha256(kept).hexdigest(), kept))
            cols = list(zip(*out))
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(cols[0], pa.int64()), pa.array(cols[1], kind), pa.array(cols[2]), pa.array(cols[3], pa.binary())], ["doc_id", "th", "n_removed", "removed", "kept_sha256", "kept"])

    return map_batches(repeated, run, CUT)


_ANCHOR = np.dtype([("key", "<u8"), ("row", "<i8")])


def _groups(e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(entries by key without repeats, first entry of each key, whether rows of that key share it).  A key's last bit: known to be shared."""
    e = np.unique(e)
    e = e[np.lexsort((e["row"], e["key"] | U64(1)))]
    key = e["key"] | U64(1)
    first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    last = np.append(first[1:], len(e)) - 1
    return e, first, (e["row"][first] != e["row"][last]) | (np.maximum.reduceat(e["key"] & U64(1), first) > 0)


def _shared_rows(e: np.ndarray, first: np.ndarray, shared: np.ndarray) -> Iterator[pa.RecordBatch]:
    """(row, its shared anchors) for entries not known to be shared before."""
    mine = e[np.repeat(shared, np.diff(np.append(first, len(e)))) & (e["key"] & U64(1) == 0)]
    if len(mine):
        mine = mine[np.argsort(mine["row"], kind="stable")]
        cut = np.flatnonzero(np.concatenate(([True], mine["row"][1:] != mine["row"][:-1], [True]))).astype(np.int32)
        anchors = pa.ListArray.from_arrays(pa.array(cut), pa.array((mine["key"] >> U64(1)).view(np.int64)))
        n = len(anchors)
        yield pa.RecordBatch.from_arrays([pa.nulls(n, pa.int32()), pa.nulls(n, pa.binary()), pa.array(mine["row"][cut[:-1]]), anchors], ["part", "blob", "row", "anchors"])


def shared_passages(docs: DataFrame, passage: int = PASSAGE, string: int = STRING) -> DataFrame:
    """row (xxhash64 of doc_id and text hash), n_shared: anchors that another row has too, for rows with any.

    A task sends one entry for each anchor, so an anchor that a third of all documents have is a row per task."""
    parts = partitions(docs.sparkSession, docs)
    schema = "part int, blob binary, row long, anchors array<long>"

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            e, first, shared = _groups(np.concatenate(held))
            yield from _shared_rows(e, first, shared)
            send = e[first]
            send["key"] |= shared.astype(U64)
            p, blobs = _packed(_part(send["key"], parts), send)
            yield pa.RecordBatch.from_arrays([pa.array(p, pa.int32()), pa.array(blobs, pa.binary()), pa.nulls(len(p), pa.int64()), pa.nulls(len(p), pa.list_(pa.int64()))], ["part", "blob", "row", "anchors"])

        for batch in batches:
            ids = batch.column(0).to_numpy()
            for lo, _, buf, off in text_slices(batch, "text"):
                starts, ends, doc = words(buf, off, EXACT_WORDS)
                g = ngram_hashes(word_hashes(buf, starts, ends, EXACT_WORDS), string)
                if len(starts) < passage:
                    continue
                at = (sliding_min((g & ~U64(0xFFFFFFFF)) | np.arange(len(g), dtype=U64), passage - string + 1) & U64(0xFFFFFFFF)).astype(np.int64)
                at = np.unique(at[doc[: len(at)] == doc[passage - 1 : passage - 1 + len(at)]])
                e = np.empty(len(at), _ANCHOR)
                e["key"], e["row"] = g[at] & ~U64(1), ids[lo + doc[at]]
                held.append(e)
                size += len(e)
                if size >= 1 << 19:
                    yield from flush()
                    held, size = [], 0
        if size:
            yield from flush()

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = []
        for batch in batches:
            packed = batch.column(1).is_valid()
            rest = batch.filter(pa.compute.invert(packed))
            if rest.num_rows:
                yield rest
            found += [np.frombuffer(x.as_buffer(), _ANCHOR) for x in batch.filter(packed).column(1)]
        if found:
            yield from _shared_rows(*_groups(np.concatenate(found)))

    rows = docs.select(F.xxhash64(docs["doc_id"].cast("long"), F.xxhash64("text")).alias("row"), docs["text"].alias("text"))
    route = F.coalesce("part", F.pmod("row", F.lit(parts)).cast("int"))
    met = rows.mapInArrow(lean(scan), schema).repartitionById(parts, route).mapInArrow(lean(meet), schema)
    return met.groupBy("row").agg(F.size(F.array_distinct(F.flatten(F.collect_list("anchors")))).cast("long").alias("n_shared"))  # of one document


def report(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, n_shared_passages (see ``shared_passages``), one row per row of docs."""
    base, repeated = repeated_spans(docs, length, min(GRAM, length))
    lost = cut(repeated, length).select(F.col("doc_id").alias("d"), F.col("th").alias("t"), "n_removed", F.size("removed").cast("long").alias("n_spans"), "kept_sha256").dropDuplicates(["d", "t"])
    out = base.join(lost, same_row(), "left").withColumn("row", F.xxhash64("doc_id", "th")).join(shared_passages(docs), "row", "left")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return out.select("doc_id", "n_bytes", zero("n_removed").alias("n_removed"), zero("n_spans").alias("n_spans"), F.coalesce("kept_sha256", "sha").alias("kept_sha256"), zero("n_shared").alias("n_shared_passages"))
