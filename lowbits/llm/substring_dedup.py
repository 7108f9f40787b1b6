"""Substring dedup by hashing lines, paragraphs or sentences (operator 8).

Texts are cut into units; a unit's digest is a 128-bit hash of its words (letters, digits and non-ASCII, A-Z lower-cased).
Of equal units the earliest by (doc_id, text hash, unit number) stays and all others go; their places in the original
text are kept as byte offsets.  Digests are packed and sent to partitions by value; a task sends only the earliest of the
equal units it meets, so no partition sees more than one entry per task of even the commonest unit.  The first scan
also hashes every text, so the texts of rows that lose nothing are read once and never move.

Unit ``BOTH`` takes the union: repeated lines go whole, short sentences in them too, and so do repeated sentences of
other lines.  Every line end ends a sentence, so what goes is told in sentences.  A line that goes has an equal
earlier one that stays or lost only sentences that stay earlier still, so of every text one copy is left.

Edge cases: units of fewer than ``least_words`` words stay; null and empty texts have no units; rows with a null
doc_id keep everything; repeated rows of one doc_id and text tie and stay together, different texts under one doc_id
are different rows.  An empty table gives an empty table; extra columns are ignored.
Digests are not compared with the words behind them: both 64-bit halves come from the same word hashes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytewords import ALNUM_WORDS, U64, text_slices, word_hashes, words
from .engine import lean, map_batches, partitions, same_row, stored
from .line_dedup import Spans, _packed, _part, line_bounds

UNIT, BOTH, LEAST_WORDS = "sentence", "line+sentence", 8
FLUSH = 1 << 19
_UNIT = np.dtype([("h1", "<u8"), ("h2", "<u8"), ("doc", "<i8"), ("th", "<i8"), ("unit", "<i4"), ("line", "<i4")])
STATE = "part int, doc_id long, th long, n_units long, sha string, unit int, line int, gone boolean, blob binary"
_SCHEMA = pa.schema([("part", pa.int32()), ("doc_id", pa.int64()), ("th", pa.int64()), ("n_units", pa.int64()), ("sha", pa.string()), ("unit", pa.int32()), ("line", pa.int32()), ("gone", pa.bool_()), ("blob", pa.binary())])


def unit_breaks(buf: np.ndarray, unit: str) -> np.ndarray:
    """Positions of the last byte of every unit but a text's last."""
    feed = buf == 10
    if unit == "paragraph":
        feed = feed & np.concatenate(([False], feed[:-1]))
    elif unit == "sentence":
        stop = (buf == 46) | (buf == 33) | (buf == 63)
        feed[1:] |= (buf[1:] == 32) & stop[:-1]
    elif unit != "line":
        raise ValueError(unit)
    return np.flatnonzero(feed)


def _edges(breaks: np.ndarray, x: int, y: int) -> np.ndarray:
    """Bounds of the units of the text at bytes x to y, from its start."""
    b = breaks[slice(*np.searchsorted(breaks, (x, y)))] + 1 - x
    return np.concatenate(([0], b, [y - x] if not len(b) or b[-1] < y - x else [])).astype(np.int64) if y > x else np.zeros(1, np.int64)


def _rows(size: int, **columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) if f.name in columns else pa.nulls(size, f.type) for f in _SCHEMA], schema=_SCHEMA)


def _sorted(e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(earliest entry of each digest, those of them that others repeat, the others that tie with none of them)."""
    e = e[np.lexsort((e["unit"], e["th"], e["doc"], e["h2"], e["h1"]))]
    new = np.concatenate(([True], (e["h1"][1:] != e["h1"][:-1]) | (e["h2"][1:] != e["h2"][:-1])))
    first = np.flatnonzero(new)
    size = np.diff(np.append(first, len(e)))
    lead = e[np.repeat(first, size)]
    later = (e["doc"] != lead["doc"]) | (e["th"] != lead["th"]) | (e["unit"] != lead["unit"])
    return e[new], e[first[np.add.reduceat(later, first) > 0]], e[later]


def _marks(kept: np.ndarray, later: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Rows for repeated units: kept ones and those that go."""
    for e, gone in ((kept, False), (later, True)):
        if len(e):
            yield _rows(len(e), doc_id=e["doc"], th=e["th"], unit=e["unit"], line=e["line"], gone=np.full(len(e), gone))


def _scan(kinds: list[str], least_words: int, parts: int):
    """A row for every text, and packed digests of the units of each kind (the first one is the one that counts)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            first, kept, later = _sorted(np.concatenate(held))
            yield from _marks(kept, later)
            p, blobs = _packed(_part(first["h1"], parts), first)
            yield _rows(len(p), part=np.array(p, np.int32), blob=blobs)

        for batch in batches:
            null, th = batch.column(0).is_null().to_numpy(False), batch.column(1).to_numpy()
            ids = batch.column(0).fill_null(0).to_numpy()
            for lo, hi, buf, off in text_slices(batch, "text"):
                starts, ends, doc = words(buf, off, ALNUM_WORDS)
                h = word_hashes(buf, starts, ends, ALNUM_WORDS)
                raw, at = buf.tobytes(), off.tolist()
                for number, kind in enumerate(kinds):
                    breaks = unit_breaks(buf, kind)
                    if not number:
                        count = [len(_edges(breaks, x, y)) - 1 for x, y in zip(at, at[1:])]
                        sha = [hashlib.sha256(raw[x:y]).hexdigest() for x, y in zip(at, at[1:])]
                        yield _rows(hi - lo, doc_id=batch.column(0).slice(lo, hi - lo), th=th[lo:hi], n_units=count, sha=sha)
                    a, b, d, k = line_bounds(buf, off, starts, doc, breaks)
                    use = (b - a >= least_words) & ~null[lo:hi][d]
                    a, b, d, k = a[use], b[use], d[use], k[use]
                    if len(a):
                        e = np.empty(len(a), _UNIT)
                        e["h1"], e["h2"], e["doc"], e["th"], e["unit"], e["line"] = Spans(h).run(a, b) + U64(number), Spans(h, 1).run(a, b) ^ U64(number), ids[lo:hi][d], th[lo:hi][d], k, number
                        held.append(e)
                        size += len(e)
                if size >= FLUSH:
                    yield from flush()
                    held, size = [], 0
        if held:
            yield from flush()

    return run


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    found = [np.frombuffer(x.as_buffer(), _UNIT) for batch in batches for x in batch.column(0)]
    if found:
        yield from _marks(*_sorted(np.concatenate(found))[1:])


def repeated_units(docs: DataFrame, unit: str = UNIT, least_words: int = LEAST_WORDS) -> tuple[DataFrame, DataFrame]:
    """(rows: doc_id, th, n_units, sha, one per row of docs; repeated: d, t, units and lines that go, n_repeated, per row with repeated units).

    th is a hash of the text; lines is filled for ``BOTH`` only."""
    parts = partitions(docs.sparkSession, docs)
    kinds = ["sentence", "line"] if unit == BOTH else [unit]
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), docs["text"].alias("text"))
    state = stored(rows.mapInArrow(lean(_scan(kinds, least_words, parts)), STATE), "units")
    met = state.where("blob is not null").select("blob", "part").repartitionById(parts, F.col("part")).mapInArrow(lean(_meet), STATE)
    marks = state.where("unit is not null").unionByName(met).select("doc_id", "th", "unit", "line", "gone")
    listed = lambda n: F.array_sort(F.collect_set(F.when(F.col("gone") & (F.col("line") == n), F.col("unit"))))
    repeated = marks.groupBy(F.col("doc_id").alias("d"), F.col("th").alias("t")).agg(listed(0).alias("units"), listed(1).alias("lines"), F.size(F.collect_set(F.struct("line", "unit"))).cast("long").alias("n_repeated"))  # of one document
    return state.where("sha is not null").select("doc_id", "th", "n_units", "sha"), repeated


def _cut(fine: str, with_kept: bool):
    spans = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        lost, lost_lines = batch.column(3), batch.column(4)
        for lo, hi, buf, off in text_slices(batch, "text"):
            breaks, feeds, raw = unit_breaks(buf, fine), unit_breaks(buf, "line"), buf.tobytes()
            removed, digest, kept, n = [], [], [], []
            for r in range(hi - lo):
                x, y = int(off[r]), int(off[r + 1])
                edge, goes = _edges(breaks, x, y), lost[lo + r].values.to_numpy()
                if len(lost_lines[lo + r]):
                    f = _edges(feeds, x, y)
                    within = [np.arange(*np.searchsorted(edge, (f[u], f[u + 1]))) for u in lost_lines[lo + r].as_py()]
                    goes = np.union1d(np.concatenate(within), goes).astype(np.int64)
                new = np.flatnonzero(np.diff(goes, prepend=-2) > 1)  # runs of units that touch
                begin, end = edge[goes[new]].tolist(), edge[goes[np.append(new[1:], len(goes)) - 1] + 1].tolist()
                text = b"".join(raw[x + p : x + q] for p, q in zip([0, *end], [*begin, y - x]))
                n.append(len(goes))
                removed.append([{"start": p, "end": q} for p, q in zip(begin, end)])
                digest.append(hashlib.sha256(text).hexdigest())
                kept.append(text if with_kept else None)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.array(n, pa.int64()), pa.array(removed, spans), pa.array(digest), pa.array(kept, pa.binary())], ["d", "t", "n_removed", "removed", "kept_sha256", "kept"])

    return run


def dedup(docs: DataFrame, unit: str = UNIT, least_words: int = LEAST_WORDS, with_kept: bool = True) -> DataFrame:
    """doc_id, n_units, n_removed, n_repeated, removed (byte offsets of the original, touching ones joined), kept_sha256 and,
    unless with_kept is false, kept (UTF-8); one row per row of docs.  n_repeated: units that also occur elsewhere, the kept ones too."""
    rows, repeated = repeated_units(docs, unit, least_words)
    repeated = stored(repeated, "repeated")
    own = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), docs["text"].alias("text"))
    losing = own.join(repeated.where("size(units) > 0 or size(lines) > 0"), same_row()).select("doc_id", "th", "text", "units", "lines")
    lost = map_batches(losing, _cut("sentence" if unit == BOTH else unit, with_kept), "d long, t long, n_removed long, removed array<struct<start:int,end:int>>, kept_sha256 string, kept binary").dropDuplicates(["d", "t"])
    out = rows.join(lost, same_row(), "left").drop("d", "t").join(repeated.select("d", "t", "n_repeated"), same_row(), "left")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    out = out.select("doc_id", "th", "n_units", zero("n_removed"), zero("n_repeated"), F.coalesce("removed", F.expr("cast(array() as array<struct<start:int,end:int>>)")).alias("removed"), F.coalesce("kept_sha256", "sha").alias("kept_sha256"), "kept")
    if not with_kept:
        return out.drop("th", "kept")
    whole = own.dropDuplicates(["doc_id", "th"]).select(F.col("doc_id").alias("d"), F.col("th").alias("t"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("whole"))
    return out.join(whole, same_row()).withColumn("kept", F.coalesce("kept", "whole")).drop("th", "d", "t", "whole")
