"""Benchmark decontamination: Wu-Manber multi-pattern search over words (operator 6).

Every window of ten consecutive words of a benchmark item is a pattern; an item of fewer words is one pattern.
Patterns of one length share a search: blocks of two words index a shift table that says how far
the scan may skip, a block with shift zero selects the patterns whose last block hashes the same, and a
direct comparison of the words confirms.  The scan runs over many stretches of a batch in step, as array
operations, so there is no loop per word.

Edge cases: null or empty texts have no words and are never hit; items without words are no patterns;
equal items are all reported; no benchmark rows means no hits.  Any number of benchmark rows: they are
taken in blocks of bounded size, each against all documents; what the blocks find is merged by a stored row number, so
repeated and null ids keep their rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytewords import ALNUM_WORDS, U64, mix, text_slices, word_hashes, words
from .engine import map_batches, stored

WINDOW, TABLE_BITS, STRETCH = 10, 20, 256


def _word_lists(texts: list[bytes]) -> list[list[bytes]]:
    keep = bytes(ALNUM_WORDS[1][b] if ALNUM_WORDS[0][b] else 32 for b in range(256))
    return [(t or b"").translate(keep).split() for t in texts]


class Searcher:
    """Patterns of one length m: shift table by block, buckets by hash of the whole pattern's last block."""

    def __init__(self, m: int, patterns: list[tuple[list[bytes], int]]):
        self.m, self.block = m, min(2, m)
        self.texts = [b" ".join(p) for p, _ in patterns]
        items: dict[bytes, list[int]] = {}
        for t, (_, i) in zip(self.texts, patterns):
            items.setdefault(t, []).append(i)
        self.texts = sorted(items)
        self.items = [sorted(set(items[t])) for t in self.texts]
        flat = b" ".join(self.texts)
        buf = np.frombuffer(flat, np.uint8)
        starts, ends, _ = words(buf, np.array([0, len(buf)]), ALNUM_WORDS)
        h = word_hashes(buf, starts, ends, ALNUM_WORDS).reshape(-1, m)
        self.shift = np.full(1 << TABLE_BITS, m - self.block + 1, np.int32)
        for j in range(m - self.block + 1):
            np.minimum.at(self.shift, self.blocks(h[:, j : j + self.block].ravel(), self.block)[:: self.block], m - self.block - j)
        last = mix(self.last_block(h))
        order = np.argsort(last, kind="stable")
        self.bucket, self.members = last[order], order

    def last_block(self, h: np.ndarray) -> np.ndarray:
        s = np.zeros(len(h), U64)
        for j in range(self.m - self.block, self.m):
            s = s * U64(0x2545F4914F6CDD1D) + h[:, j]
        return s

    @staticmethod
    def blocks(h: np.ndarray, size: int) -> np.ndarray:
        """Table slot of the block that starts at each word (the last size - 1 are not blocks)."""
        s = h.copy()
        if size == 2:
            s[:-1] = s[:-1] * U64(0x2545F4914F6CDD1D) + h[1:]
        return (mix(s) >> U64(64 - TABLE_BITS)).astype(np.int64)

    def search(self, h: np.ndarray, doc: np.ndarray, word) -> Iterator[tuple[int, int]]:
        """(first word, pattern) of every occurrence; word(a, b) gives the bytes of words a to b joined by blanks."""
        n, m, b = len(h), self.m, self.block
        if n < m:
            return
        slot = self.blocks(h, b)
        whole = h.copy()
        if b == 2:
            whole[:-1] = whole[:-1] * U64(0x2545F4914F6CDD1D) + h[1:]
        whole = mix(whole)  # last-block hash by the block's first word
        # pos: first word of the window's last block; windows in a stretch end within it, or start in it
        lo = np.arange(m - b, n - b + 1, STRETCH)
        hi = np.minimum(lo + STRETCH, n - b + 1)
        while len(lo):
            skip = self.shift[slot[lo]]
            at = lo[skip == 0]
            if len(at):
                at = at[doc[at + b - 1] == doc[at - (m - b)]]
            if len(at):
                left = np.searchsorted(self.bucket, whole[at], side="left")
                right = np.searchsorted(self.bucket, whole[at], side="right")
                for p, x, y in zip(at[k := right > left].tolist(), left[k].tolist(), right[k].tolist()):
                    first = p - (m - b)
                    text = word(first, first + m)
                    for q in self.members[x:y].tolist():
                        if self.texts[q] == text:
                            yield first, q
            lo = lo + np.maximum(skip, 1)
            k = lo < hi
            lo, hi = lo[k], hi[k]


def build(items: list[tuple[int, bytes]]) -> list[Searcher]:
    """A searcher for each pattern length that occurs."""
    by: dict[int, list] = {}
    for (i, _), w in zip(items, _word_lists([t for _, t in items])):
        if 0 < len(w) < WINDOW:
            by.setdefault(len(w), []).append((w, i))
        for k in range(len(w) - WINDOW + 1):
            by.setdefault(WINDOW, []).append((w[k : k + WINDOW], i))
    return [Searcher(m, p) for m, p in sorted(by.items())]


def _joiner(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray):
    raw, low = buf.tobytes(), bytes(ALNUM_WORDS[1])
    return lambda a, b: b" ".join(raw[s:e] for s, e in zip(starts[a:b].tolist(), ends[a:b].tolist())).translate(low)


def _blocks(benchmark: DataFrame, block_mb: int) -> Iterator:
    """Searchers for blocks of at most about block_mb of benchmark text, as broadcasts."""
    bench = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").alias("text")).where("item_id is not null and text is not null")
    total = bench.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-total // (block_mb << 20)))
    for k in range(blocks):
        mine = bench if blocks == 1 else bench.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == k)
        rows = [(r.item_id, r.text.encode()) for r in mine.collect()]  # bounded by block_mb
        yield benchmark.sparkSession.sparkContext.broadcast(build(rows))


FOUND = "row long, doc_id long, n_words long, hit array<struct<first:int,last:int>>, items array<long>"


def _scan(docs: DataFrame, searchers) -> DataFrame:
    """row, doc_id, n_words, runs of hit words and items found, for one block of benchmark rows."""
    schema = pa.schema([("row", pa.int64()), ("doc_id", pa.int64()), ("n_words", pa.int64()), ("hit", pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32())]))), ("items", pa.list_(pa.int64()))])

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for lo, hi, buf, off in text_slices(batch, "text"):
            starts, ends, doc = words(buf, off, ALNUM_WORDS)
            h = word_hashes(buf, starts, ends, ALNUM_WORDS)
            bounds = np.searchsorted(starts, off)
            word = _joiner(buf, starts, ends)
            mark = np.zeros(len(h) + 1, np.int32)
            items: dict[int, set] = {}
            for s in searchers.value:
                for first, q in s.search(h, doc, word):
                    mark[first] += 1
                    mark[first + s.m] -= 1
                    items.setdefault(int(doc[first]), set()).update(s.items[q])
            hit = np.cumsum(mark[:-1]) > 0
            runs = [[] for _ in range(hi - lo)]
            for d in items:
                a, b = int(bounds[d]), int(bounds[d + 1])
                edge = np.flatnonzero(np.diff(np.concatenate(([0], hit[a:b].astype(np.int8), [0]))))
                runs[d] = [{"first": int(x), "last": int(y) - 1} for x, y in zip(edge[::2], edge[1::2])]
            yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(lo, hi - lo) for c in (0, 1)), pa.array(np.diff(bounds)), pa.array(runs, schema.field("hit").type), pa.array([sorted(items.get(d, ())) for d in range(hi - lo)], schema.field("items").type)], schema=schema)

    return map_batches(docs, run, FOUND)


def contamination(docs: DataFrame, benchmark: DataFrame, block_mb: int = 16, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, hit (runs of word numbers, both ends included) and items (sorted ids), one row per row of docs.

    block_mb bounds the benchmark text held at once: larger benchmarks are searched for in several passes."""
    docs = docs.select(F.monotonically_increasing_id().alias("row"), docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    blocks = list(_blocks(benchmark, block_mb))
    if len(blocks) == 1:
        return _scan(docs, blocks[0]).drop("row")
    docs = stored(docs, "decontam")  # every block must see the same row numbers
    parts = [_scan(docs, s) for s in blocks]
    merged = parts[0]
    for p in parts[1:]:
        merged = merged.unionByName(p)
    runs = merged.groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.max("n_words").alias("n_words"), F.flatten(F.collect_list("hit")).alias("runs"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    whole = """aggregate(array_sort(runs), cast(array() as array<struct<first:int,last:int>>), (s, x) ->
        case when size(s) > 0 and element_at(s, -1).last + 1 >= x.first
             then concat(slice(s, 1, size(s) - 1), array(named_struct('first', element_at(s, -1).first, 'last', greatest(element_at(s, -1).last, x.last))))
             else concat(s, array(x)) end)"""
    return runs.select("doc_id", "n_words", F.expr(whole).alias("hit"), "items")


def report(found: DataFrame) -> DataFrame:
    """The digest columns of a contamination table."""
    return found.select(
        "doc_id",
        "n_words",
        F.expr("aggregate(hit, 0L, (s, x) -> s + x.last - x.first + 1)").alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", F.array_sort(F.col("items").cast("array<string>"))), 256).alias("items_sha256"),
        (F.size("hit") > 0).alias("contaminated"),
    )


def clean(docs: DataFrame, benchmark: DataFrame, block_mb: int = 16, text_col: str = "text") -> DataFrame:
    """The rows of docs, all columns, that hold no occurrence of any window.  Nothing is shuffled."""
    for searchers in _blocks(benchmark, block_mb):

        def run(batch: pa.RecordBatch, searchers=searchers) -> Iterator[pa.RecordBatch]:
            keep = np.ones(batch.num_rows, bool)
            for lo, _, buf, off in text_slices(batch, text_col):
                starts, ends, doc = words(buf, off, ALNUM_WORDS)
                h = word_hashes(buf, starts, ends, ALNUM_WORDS)
                for s in searchers.value:
                    for first, _ in s.search(h, doc, _joiner(buf, starts, ends)):
                        keep[lo + doc[first]] = False
            yield batch.filter(pa.array(keep))

        docs = map_batches(docs, run, docs.schema)
    return docs
