"""Line dedup by a deletion-neighbourhood join over words (operator 3).

A line's form is its sequence of words (letters, digits and non-ASCII, A-Z lower-cased).  A line goes if an earlier line, by
(doc_id, line number), has the same form, or a form within one word edit (insert, delete or replace) where both have
at least ``LEAST_WORDS`` words.  "Earlier" looks at all lines, kept or not, so the result has no order of its own.

Only the first line of each form takes part in the join.  Lossless screen: forms within one edit share their first
or their second half.  Forms that share a half emit every variant with one word deleted, as hashed keys:
(variant, position) keys meet replacements, (variant) keys meet a form that is the variant itself.  All forms with
one variant at one position are one edit apart, so only the earliest of them stands for both kinds of key, first per
task, then over all tasks: the others go by it anyway.  A key holds at most one entry for each position, however many
lines share the variant, and no group is expanded to pairs.  The words of every pair found are compared.

Edge cases: null and empty texts have no words; lines without words stay; repeated rows of one doc_id and text tie and
stay together, lines of two texts under one doc_id and line number are ordered by a hash of the text; rows with a null
doc_id take no part and keep all their lines.  An empty table gives an empty table;
other columns are kept by ``drop_lines`` and ignored by ``repeated_lines``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytewords import ALNUM_WORDS, U64, mix, text_slices, word_hashes, words
from .engine import lean, map_batches, partitions, stored

LEAST_WORDS = 8
_K = [np.uint64(0x2545F4914F6CDD1D), np.uint64(0xD1342543DE82EF95)]
_M64 = (1 << 64) - 1
ROW = "kind int, part int, doc_id long, line long, n int, h1 long, h2 long, blob binary"
_SCHEMA = pa.schema([("kind", pa.int32()), ("part", pa.int32()), ("doc_id", pa.int64()), ("line", pa.int64()), ("n", pa.int32()), ("h1", pa.int64()), ("h2", pa.int64()), ("blob", pa.binary())])
LINE, HALVES, SHARED = range(3)
_HALF = np.dtype([("key", "<u8"), ("form", "<u8")])
_SPOT = np.dtype([("key", "<u8"), ("doc", "<i8"), ("line", "<i8"), ("role", "<i4")])
#: What an entry is; from SHORTER on, a form without the word at position role - SHORTER.
REPLACE, SELF, SHORTER = 0, 1, 2
#: A line's place in its document: its number, then so many bits of a hash of the text, which tell texts of one id apart.
TAG_BITS = 24


def _tag(text: F.Column) -> F.Column:
    return F.xxhash64(text).bitwiseAND(F.lit((1 << TAG_BITS) - 1))


def _part(h: np.ndarray, parts: int) -> np.ndarray:
    return (((h >> U64(40)) * U64(parts)) >> U64(24)).astype(np.int64)


def _powers(k: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for b in (k, U64(pow(int(k), -1, 1 << 64))):
        p = np.full(n, b, U64)
        p[:1] = 1
        out.append(np.cumprod(p, dtype=U64))
    return out[0], out[1]


class Spans:
    """Hashes of runs of words, from running sums."""

    def __init__(self, h: np.ndarray, which: int = 0):
        self.p, self.q = _powers(_K[which], len(h) + 1)
        self.sum = np.zeros(len(h) + 1, U64)
        np.cumsum(h * self.p[: len(h)], out=self.sum[1:], dtype=U64)

    def raw(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return (self.sum[b] - self.sum[a]) * self.q[a]

    def run(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return mix(self.raw(a, b) + (b - a).astype(U64))

    def without(self, a: np.ndarray, b: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Hash of words a..b with word i left out; equals run() of such words."""
        left = self.raw(a, i)
        right = (self.sum[b] - self.sum[i + 1]) * self.q[i + 1] * self.p[i - a]
        return mix(left + right + (b - a - 1).astype(U64))


def line_bounds(buf: np.ndarray, off: np.ndarray, starts: np.ndarray, doc: np.ndarray, breaks: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """(first word, end word, document, line number) of every line that has words.  breaks: last bytes of the lines, if not line feeds."""
    breaks = np.flatnonzero(buf == 10) if breaks is None else breaks
    if not len(starts):
        z = np.zeros(0, np.int64)
        return z, z, z, z
    seen = np.searchsorted(breaks, starts)
    base = np.searchsorted(breaks, off[:-1])
    first = np.flatnonzero(np.concatenate(([True], (seen[1:] != seen[:-1]) | (doc[1:] != doc[:-1]))))
    return first, np.append(first[1:], len(starts)), doc[first], seen[first] - base[doc[first]]


def _rows(kind: int, part, doc_id, line, n, h1, h2, blob) -> pa.RecordBatch:
    size = len(part)
    col = lambda x, t: pa.array(x, t) if x is not None else pa.nulls(size, t)
    return pa.RecordBatch.from_arrays([pa.array(np.full(size, kind, np.int32)), *(col(x, f.type) for x, f in zip((part, doc_id, line, n, h1, h2, blob), list(_SCHEMA)[1:]))], schema=_SCHEMA)


def _packed(part: np.ndarray, entries: np.ndarray) -> tuple[list[int], list[bytes]]:
    order = np.argsort(part, kind="stable")
    part, entries = part[order], entries[order]
    cut = np.append(np.flatnonzero(np.diff(part)) + 1, len(part))
    at = np.append(0, cut[:-1])
    return [int(part[a]) for a in at.tolist()], [entries[a:b].tobytes() for a, b in zip(at.tolist(), cut.tolist())]


def _shared_forms(e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(forms under keys with more than one form, one entry per key)."""
    e = e[np.lexsort((e["form"], e["key"]))]
    key, form = e["key"], e["form"]
    new = np.concatenate(([True], key[1:] != key[:-1]))
    e, new = e[(k := new | np.concatenate(([True], form[1:] != form[:-1])))], new[k]
    alone = new & np.concatenate((new[1:], [True]))
    return np.unique(e["form"][~alone]), e[new]


def _lines(parts: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, tag = batch.column(0), batch.column(2).to_numpy()
            for lo, hi, buf, off in text_slices(batch, "text"):
                starts, ends, doc = words(buf, off, ALNUM_WORDS)
                a, b, d, line = line_bounds(buf, off, starts, doc)
                if not len(a):
                    continue
                line = line << TAG_BITS | tag[lo:hi][d]
                h = word_hashes(buf, starts, ends, ALNUM_WORDS)
                s = Spans(h)
                form, second = s.run(a, b), Spans(h, 1).run(a, b)
                own = ids.slice(lo, hi - lo).take(pa.array(d))
                place = mix(own.to_numpy().astype(U64) ^ mix(line.astype(U64)))  # lines only pass by, so copies of one may lie anywhere
                yield _rows(LINE, _part(place, parts).astype(np.int32), own, line, (b - a).astype(np.int32), form.view(np.int64), second.view(np.int64), None)
                k = b - a >= LEAST_WORDS
                a, b, form = a[k], b[k], form[k]
                if not len(a):
                    continue
                e = []
                for shorter in (0, 1):
                    m = b - a - shorter
                    half = m // 2
                    for side, x in ((0, s.run(a, a + half)), (1, s.run(b - (m - half), b))):
                        part = np.empty(len(a), _HALF)
                        part["key"], part["form"] = mix(x + m.astype(U64) * U64(2) + U64(side)), form
                        e.append(part)
                forms, rest = _shared_forms(np.concatenate(e))
                if len(forms):
                    yield _rows(SHARED, _part(forms, parts).astype(np.int32), None, None, None, forms.view(np.int64), None, None)
                p, blobs = _packed(_part(rest["key"], parts), rest)
                yield _rows(HALVES, p, None, None, None, None, None, blobs)

    return run


def _screen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    found = []
    for batch in batches:
        kind = batch.column(0).to_numpy()
        rest = batch.filter(pa.array(kind != HALVES))
        if rest.num_rows:
            yield rest
        found += [np.frombuffer(x.as_buffer(), _HALF) for x in batch.filter(pa.array(kind == HALVES)).column(7)]
    if found:
        forms, _ = _shared_forms(np.concatenate(found))
        if len(forms):
            yield _rows(SHARED, np.zeros(len(forms), np.int32), None, None, None, forms.view(np.int64), None, None)


_PAIR = "part int, doc_id long, line long, by_doc long, by_line long, blob binary, words string"
_PAIR_SCHEMA = pa.schema([("part", pa.int32()), ("doc_id", pa.int64()), ("line", pa.int64()), ("by_doc", pa.int64()), ("by_line", pa.int64()), ("blob", pa.binary()), ("words", pa.string())])


def _pair_rows(part, doc, line, by_doc=None, by_line=None, blob=None, text=None) -> pa.RecordBatch:
    size = len(part)
    return pa.RecordBatch.from_arrays([pa.array(x, f.type) if x is not None else pa.nulls(size, f.type) for x, f in zip((part, doc, line, by_doc, by_line, blob, text), _PAIR_SCHEMA)], schema=_PAIR_SCHEMA)


def _earlier(e: np.ndarray) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray]]]:
    """(entries that others still have to meet, [(later, earlier)] found among e).

    Of entries with one key and role only the earliest stays.  A form that shares a variant and its position with an earlier one
    goes by that one, so what equals the variant need not meet it too."""
    e = e[np.lexsort((e["line"], e["doc"], e["role"], e["key"]))]
    key, role = e["key"], e["role"]
    new = np.concatenate(([True], (key[1:] != key[:-1]) | (role[1:] != role[:-1])))
    first = np.flatnonzero(new)
    lead = np.repeat(first, np.diff(np.append(first, len(e))))
    later = (role == REPLACE) & ~new
    pairs = [(e[later], e[lead[later]])]
    # a form that equals a variant, against the forms left with that variant: self entries sort before shorter ones
    e = e[new]
    key, role = e["key"], e["role"]
    begin = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    top = np.repeat(begin, np.diff(np.append(begin, len(e))))
    meets = (role >= SHORTER) & (role[top] == SELF)
    s, d = e[top[meets]], e[meets]
    before = (s["doc"] < d["doc"]) | ((s["doc"] == d["doc"]) & (s["line"] < d["line"]))
    pairs += [(d[before], s[before]), (s[~before], d[~before])]
    return e, pairs


def _variants(parts: int):
    """Variants of the chosen lines of each document: packed entries, pairs met within the task, and the lines' words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        low = bytes(ALNUM_WORDS[1])
        for batch in batches:
            ids, tag, chosen = batch.column(0).to_numpy(), batch.column(2).to_numpy(), batch.column(3).to_pylist()
            for lo, hi, buf, off in text_slices(batch, "text"):
                starts, ends, doc = words(buf, off, ALNUM_WORDS)
                a, b, d, line = line_bounds(buf, off, starts, doc)
                h = word_hashes(buf, starts, ends, ALNUM_WORDS)
                want = np.array([(k, x >> TAG_BITS) for k, xs in enumerate(chosen[lo:hi]) for x in set(xs) if x & (1 << TAG_BITS) - 1 == tag[lo + k]], np.int64).reshape(-1, 2)
                k = np.isin(d << 32 | line, want[:, 0] << 32 | want[:, 1])
                a, b, d, line = a[k], b[k], d[k], line[k]
                if not len(a):
                    continue
                line = line << TAG_BITS | tag[lo:hi][d]
                n, s = b - a, Spans(h)
                i = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
                aa, bb, owner = np.repeat(a, n), np.repeat(b, n), np.repeat(np.arange(len(a)), n)
                v = s.without(aa, bb, aa + i)
                doc_ids = ids[lo:hi][d]
                e = np.empty(2 * len(v) + len(a), _SPOT)
                e["key"] = np.concatenate((mix(v + (i.astype(U64) + U64(1)) * U64(0x9E3779B97F4A7C15)), v, s.run(a, b)))
                e["doc"], e["line"] = doc_ids[np.concatenate((owner, owner, np.arange(len(a))))], line[np.concatenate((owner, owner, np.arange(len(a))))]
                e["role"] = np.concatenate((np.full(len(v), REPLACE), SHORTER + i, np.full(len(a), SELF)))
                e = np.unique(e)
                rest, pairs = _earlier(e)
                for x, y in pairs:
                    if len(x):
                        yield _pair_rows(np.zeros(len(x), np.int32), x["doc"], x["line"], y["doc"], y["line"])
                p, blobs = _packed(_part(rest["key"], parts), rest)
                yield _pair_rows(p, None, None, blob=blobs)
                raw = buf.tobytes()
                st, en = starts.tolist(), ends.tolist()
                text = [b" ".join(raw[st[w] : en[w]] for w in range(x, y)).translate(low).decode() for x, y in zip(a.tolist(), b.tolist())]
                yield _pair_rows((np.arange(len(a)) % parts).astype(np.int32), doc_ids, line, text=text)

    return run


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    found = []
    for batch in batches:
        packed = batch.column(5).is_valid()
        rest = batch.filter(pa.compute.invert(packed))
        if rest.num_rows:
            yield rest
        found += [np.frombuffer(x.as_buffer(), _SPOT) for x in batch.filter(packed).column(5)]
    if found:
        for x, y in _earlier(np.concatenate(found))[1]:
            if len(x):
                p = np.unique(np.rec.fromarrays([x["doc"], x["line"], y["doc"], y["line"]], names="a,b,c,d"))
                yield _pair_rows(np.zeros(len(p), np.int32), p["a"], p["b"], p["c"], p["d"])


def within_one_edit(a: list, b: list) -> bool:
    """Whether one insert, delete or replace, or none, turns a into b."""
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > 1:
        return False
    i = next((k for k, (x, y) in enumerate(zip(a, b)) if x != y), len(a))
    return a[i + (len(a) == len(b)) :] == b[i + 1 :]


def repeated_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, tag of the text and the sorted numbers (from 0) of the lines that go, for documents that lose any."""
    parts = partitions(docs.sparkSession, docs)
    docs = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"), _tag(docs[text_col]).alias("tag")).where("doc_id is not null")
    state = stored(docs.mapInArrow(lean(_lines(parts)), ROW).repartitionById(parts, F.col("part")).mapInArrow(lean(_screen), ROW), "lines")
    lines = state.where(f"kind = {LINE}").select("doc_id", "line", "n", "h1", "h2")
    shared = state.where(f"kind = {SHARED}").select(F.col("h1").alias("form")).distinct()
    forms = stored(lines.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "line")).alias("first"), F.max("n").alias("n"), F.count("*").alias("many")), "forms")
    chosen = forms.where(f"n >= {LEAST_WORDS}").join(shared, forms["h1"] == shared["form"], "left_semi")
    chosen = chosen.groupBy(F.col("first.doc_id").alias("doc_id")).agg(F.collect_list("first.line").alias("lines"))  # lines of one document
    found = stored(docs.join(chosen, "doc_id").select("doc_id", "text", "tag", "lines").mapInArrow(lean(_variants(parts)), _PAIR).repartitionById(parts, F.col("part")).mapInArrow(lean(_meet), _PAIR), "pairs")
    texts = found.where("words is not null").select(F.col("doc_id").alias("d"), F.col("line").alias("l"), "words").dropDuplicates(["d", "l"])
    pairs = found.where("by_doc is not null").select("doc_id", "line", "by_doc", "by_line").distinct()
    both = pairs.join(texts.withColumnRenamed("words", "mine"), (pairs["doc_id"] == F.col("d")) & (pairs["line"] == F.col("l"))).drop("d", "l")
    both = both.join(texts, (both["by_doc"] == F.col("d")) & (both["by_line"] == F.col("l")))

    def verify(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        ok = [within_one_edit(x.split(" "), y.split(" ")) for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
        yield batch.filter(pa.array(ok, pa.bool_())).select([0, 1])

    near = map_batches(both.select("doc_id", "line", "mine", "words"), verify, "doc_id long, line long").distinct()
    near = near.select(F.struct("doc_id", "line").alias("near"))
    bad = forms.join(near, forms["first"] == near["near"], "left").where("near is not null or many > 1").select(F.col("h1").alias("x"), F.col("h2").alias("y"), "first", F.col("near").isNotNull().alias("gone"))
    out = lines.join(bad, (lines["h1"] == bad["x"]) & (lines["h2"] == bad["y"])).where("gone or struct(doc_id, line) > first")
    number, tag = F.shiftright("line", TAG_BITS).cast("int"), F.col("line").bitwiseAND(F.lit((1 << TAG_BITS) - 1))
    return out.groupBy("doc_id", tag.alias("tag")).agg(F.array_sort(F.collect_set(number)).alias("removed"))  # of one document


def line_report(docs: DataFrame) -> DataFrame:
    """doc_id, n_lines, n_removed, removed (line numbers), one row per row of docs."""
    gone = repeated_lines(docs).withColumnsRenamed({"doc_id": "d", "tag": "t"})
    own = docs.select(docs["doc_id"].cast("long").alias("doc_id"), _tag(docs["text"]).alias("tag"), F.when(F.length(docs["text"]) > 0, F.size(F.split(docs["text"], "\n"))).otherwise(0).cast("long").alias("n_lines"))
    out = own.join(gone, (F.col("doc_id") == F.col("d")) & (F.col("tag") == F.col("t")), "left")
    none = F.expr("cast(array() as array<int>)")
    return out.select("doc_id", "n_lines", F.coalesce(F.size("removed"), F.lit(0)).cast("long").alias("n_removed"), F.coalesce("removed", none).alias("removed"))


def drop_lines(docs: DataFrame) -> DataFrame:
    """docs, all columns, without repeated lines; n_chars, where there is one, counts what is left."""
    gone = repeated_lines(docs)
    text, removed = docs["text"], gone["removed"]
    kept = F.array_join(F.filter(F.split(text, "\n"), lambda x, i: ~F.array_contains(removed, i)), "\n")
    out = {c: docs[c] for c in docs.columns} | {"text": F.when(removed.isNull(), text).otherwise(kept)}
    if "n_chars" in docs.columns:
        out["n_chars"] = F.when(removed.isNull(), docs["n_chars"]).otherwise(F.length(kept)).cast(docs.schema["n_chars"].dataType)
    both = docs.join(gone, (docs["doc_id"].cast("long") == gone["doc_id"]) & (_tag(text) == gone["tag"]), "left")
    return both.select(*(x.alias(c) for c, x in out.items()))
