"""N-gram Jaccard join by universe-partition pigeonhole (operator 7).

A document's set is its distinct w-word shingles.  Documents link when the Jaccard similarity of their sets is
at least 3/4; classes are the connected components of all links.  The result is exact.

1. Count: distinct sets send their tokens, packed, to partitions by token; a set can only link if
   three quarters of its tokens occur in another set.  Copies of a set meet in its fingerprint, so they count once.
2. Allocate: tokens of the sets left are hashed to segments by size band.  Two linked sets differ in at
   most H tokens, so segments whose allowances add up to H + 1 can't all differ by more.  Each token carries the class
   of its document frequency (its binary logarithm), and each class is served the way that costs less for a unit of
   allowance: fine segments, compared as they are (allowance 1), whose keys meet as many sets as have the token, or coarse
   segments compared with one-deletion neighbourhoods (allowance 2), which send more keys that meet next to none by chance.
   Segments are spent in the order of their cost, so sets with enough cheap tokens spend nothing on dear ones.
3. Join: equal keys are linked to the smallest fingerprint that has them, first within a task, then over
   all tasks, so no group is ever expanded to pairs.  Components of these edges hold every possible link.
4. Verify, exactly, by matrix products over blocks of bounded size.  First every candidate against the smallest one it was
   joined to, which costs no more than the candidates.  Where these links already hold a component together, it is done;
   of any other the greatest part that hangs together is the core, and the strays alone are compared with each other
   and with the core.  True links give the final components.

Words are runs of other characters than space and controls 9 to 13, A-Z lower-cased.  Fewer than w words: the whole
sequence is the one shingle.  Null, empty or wordless texts: the empty set, linked with nothing.  Repeated rows
and ties need no rule: a class is named by its smallest doc_id.  A null doc_id keeps its row, with component null, and
links others as any row does; rows are told apart by id and text hash, so two texts under one id have a class each.
Tokens and sets are identified by 64-bit hashes.  Extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytewords import U64, mix, shingle_sets, text_slices
from .engine import components, lean, map_batches, partitions, same_row, stored

W, LOCALLY_FREQUENT, BLOCK = 5, 64, 1024
#: Costs of a key that is sent and of a set met under it; tokens of a coarse segment.
KEY_COST, MEETING_COST, COARSE = 1.0, 0.1, 4
#: Classes of document frequency; the last one: frequent within a single task already.
CLASSES = 16
FLUSH_TOKENS = 1 << 20
ROW = "kind int, part int, doc_id long, n long, fp long, blob binary, th long"
REGISTRY, TOKENS, MATCHED, KEYS, EDGES, SIZES = range(6)
_SCHEMA = pa.schema([("kind", pa.int32()), ("part", pa.int32()), ("doc_id", pa.int64()), ("n", pa.int64()), ("fp", pa.int64()), ("blob", pa.binary()), ("th", pa.int64())])
_ENTRY = np.dtype([("fp", "<u8"), ("key", "<u8")])
_PAIR = np.dtype([("a", "<u8"), ("b", "<u8")])


def _part(h: np.ndarray, parts: int) -> np.ndarray:
    return (((h >> U64(40)) * U64(parts)) >> U64(24)).astype(np.int64)


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) if rows else [[]] * 6
    return pa.RecordBatch.from_arrays([*(pa.array(c, f.type) for c, f in zip(cols, _SCHEMA)), pa.nulls(len(rows), pa.int64())], schema=_SCHEMA)


def _by_part(kind: int, part: np.ndarray, entries: np.ndarray) -> list[tuple]:
    order = np.argsort(part, kind="stable")
    part, entries = part[order], entries[order]
    cut = np.flatnonzero(np.diff(part)) + 1
    return [(kind, int(part[a]), None, None, None, entries[a:b].tobytes()) for a, b in zip(np.append(0, cut), np.append(cut, len(part))) if b > a]


def _sized(kind: int, sets: list[tuple[int, int]], parts: int, ids: pa.Array | None = None, th: pa.Array | None = None) -> pa.RecordBatch:
    """Rows (size, fingerprint): with ids dealt by row, as copies of one set may be a third of all rows, else by fingerprint."""
    n, f = np.array([x[0] for x in sets], np.int64), np.array([x[1] for x in sets], U64)
    null = lambda t: pa.nulls(len(n), t)
    own = f if ids is None else mix(mix(ids.fill_null(0).to_numpy(zero_copy_only=False).astype(U64)) ^ th.to_numpy().astype(U64))
    columns = [pa.array(np.full(len(n), kind, np.int32)), pa.array(_part(own, parts).astype(np.int32)), null(pa.int64()) if ids is None else ids, pa.array(n), pa.array(f.view(np.int64)), null(pa.binary()), null(pa.int64()) if th is None else th]
    return pa.RecordBatch.from_arrays(columns, schema=_SCHEMA)


def _emit(w: int, parts: int):
    """Registry rows of all documents, dealt by row, and sizes and packed tokens of the distinct sets a task meets, dealt by set and token."""

    def pack(held: list, fps: list) -> list[tuple]:
        sizes = np.array([len(s) for s in held])
        tok, doc = np.concatenate(held), np.repeat(np.arange(len(held)), sizes)
        fp = np.array(fps, U64)
        out = []
        order = np.argsort(tok, kind="stable")
        t = tok[order]
        first = np.flatnonzero(np.concatenate(([True], t[1:] != t[:-1])))
        count = np.diff(np.append(first, len(t)))
        many = count >= LOCALLY_FREQUENT
        hot_tok, hot_n = t[first[many]], count[many]
        if len(hot_tok):
            flag = np.zeros(len(tok), bool)
            flag[order] = np.repeat(many, count)
            e = np.empty(int(flag.sum()), _ENTRY)
            e["fp"], e["key"] = fp[doc[flag]], _short(tok[flag], _part(tok[flag], parts), np.full(int(flag.sum()), CLASSES - 1))
            out += _by_part(MATCHED, _part(e["fp"], parts), e)
            tok, doc = tok[~flag], doc[~flag]
        p = _part(tok, parts)
        order = np.argsort(p, kind="stable")
        tok, doc, p = tok[order], doc[order], p[order]
        hot_p = _part(hot_tok, parts)
        low = np.ascontiguousarray(tok).view(np.uint8).reshape(-1, 8)[:, :5]
        bounds = np.searchsorted(p, np.arange(parts + 1))
        for k in range(parts):
            a, b = int(bounds[k]), int(bounds[k + 1])
            mine = hot_p == k
            if a == b and not mine.any():
                continue
            d, c = np.unique(doc[a:b], return_counts=True)
            head = np.array([len(d), int(mine.sum())], "<u4")
            out.append((TOKENS, k, None, None, None, b"".join((head.tobytes(), fp[d].tobytes(), c.astype("<u4").tobytes(), hot_tok[mine].tobytes(), hot_n[mine].astype("<u4").tobytes(), low[a:b].tobytes()))))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        held, fps, size = [], [], 0
        for batch in batches:
            ids = batch.column(0)
            for lo, hi, buf, off in text_slices(batch, "text"):
                registry, new = [], []
                for s in shingle_sets(buf, off, w):
                    fp = int.from_bytes(hashlib.blake2b(s.tobytes(), digest_size=8).digest(), "little")
                    registry.append((len(s), fp))
                    if len(s) and fp not in seen:
                        if len(seen) < 1 << 20:
                            seen.add(fp)
                        new.append((len(s), fp))
                        held.append(s)
                        fps.append(fp)
                        size += len(s)
                yield _sized(REGISTRY, registry, parts, ids.slice(lo, hi - lo), batch.column(2).slice(lo, hi - lo))
                if new:
                    yield _sized(SIZES, new, parts)
                if size >= FLUSH_TOKENS:
                    yield _rows(pack(held, fps))
                    held, fps, size = [], [], 0
        if held:
            yield _rows(pack(held, fps))

    return run


def _short(token: np.ndarray, part: np.ndarray, kind: np.ndarray) -> np.ndarray:
    """What a token's partition sees of it, its low 40 bits and the partition, and in the last bits the class of its frequency."""
    return (mix(token & U64((1 << 40) - 1) | part.astype(U64) << U64(40)) & ~U64(CLASSES - 1)) | kind.astype(U64)


def exact_cost(kind: int) -> float:
    """Of a unit of allowance, where a segment is compared as it is: one key, which meets every set with the token."""
    return KEY_COST + MEETING_COST * 2.0**kind


def deletion_cost() -> float:
    """Of a unit of allowance, where a segment is compared with one-deletion neighbourhoods: a key for the whole and one for each token left out."""
    return (COARSE + 1) * KEY_COST / 2


def allocation() -> np.ndarray:
    """For each class: its place in the order of cost; classes served by deletion neighbourhoods share the last place, CLASSES."""
    return np.array([c if exact_cost(c) <= deletion_cost() else CLASSES for c in range(CLASSES)])


def _match(parts: int):
    """Tokens that occur in more than one set, by set.  All other rows pass through."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, fps, hot, hot_n = [], [], [], []
        for batch in batches:
            kind = batch.column(0).to_numpy()
            rest = batch.filter(pa.array(kind != TOKENS))
            if rest.num_rows:
                yield rest
            mine = batch.filter(pa.array(kind == TOKENS))
            for part, blob in zip(mine.column(1).to_pylist(), mine.column(5)):
                raw = np.frombuffer(blob.as_buffer(), np.uint8)
                nd, nh = (int(x) for x in raw[:8].view("<u4"))
                at = 8
                fp = raw[at : at + 8 * nd].copy().view("<u8")
                at += 8 * nd
                c = raw[at : at + 4 * nd].copy().view("<u4")
                at += 4 * nd
                h = raw[at : at + 8 * nh].copy().view("<u8")
                at += 8 * nh
                hn = raw[at : at + 4 * nh].copy().view("<u4")
                at += 4 * nh
                low = np.zeros(((len(raw) - at) // 5, 8), np.uint8)
                low[:, :5] = raw[at:].reshape(-1, 5)
                keys.append(low.view("<u8").ravel() | U64(part) << U64(40))
                fps.append(np.repeat(fp, c))
                hot.append((h & U64((1 << 40) - 1)) | U64(part) << U64(40))
                hot_n.append(hn)
        if not keys:
            return
        key, fp = np.concatenate(keys), np.concatenate(fps)
        del keys, fps
        known = np.unique(np.concatenate(hot))
        order = np.argsort(key, kind="stable")
        key, fp = key[order], fp[order]
        new = np.concatenate(([True], key[1:] != key[:-1])) if len(key) else np.zeros(0, bool)
        again = ~new
        again[:-1] |= ~new[1:]
        if len(known) and len(key):
            at = np.minimum(np.searchsorted(known, key), len(known) - 1)
            sure = known[at] == key
        else:
            sure = np.zeros(len(key), bool)
        k = again | sure
        key, fp, sure = key[k], fp[k], sure[k]
        order = np.lexsort((fp, key))
        key, fp, sure = key[order], fp[order], sure[order]
        if len(key):
            k = np.concatenate(([True], (key[1:] != key[:-1]) | (fp[1:] != fp[:-1])))
            key, fp, sure = key[k], fp[k], sure[k]
            first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
            df = np.diff(np.append(first, len(key)))
            df = np.repeat(df, df)
            k = (df > 1) | sure
            e = np.empty(int(k.sum()), _ENTRY)
            e["fp"], e["key"] = fp[k], _short(key[k], key[k] >> U64(40), np.where(sure[k], CLASSES - 1, np.minimum(np.log2(df[k]).astype(np.int64), CLASSES - 2)))
            yield _rows(_by_part(MATCHED, _part(e["fp"], parts), e))

    return run


def bands(n: int) -> list[tuple[int, int]]:
    """(upper size of the band, most different tokens H) for each band in which a set of n tokens can have a partner."""
    upper = 128
    while upper < n:
        upper *= 4
    most = 4 * n // 3
    out = [(upper, (n + min(upper, most)) // 7)]
    if most > upper:
        out.append((upper * 4, (n + most) // 7))
    return out


def segment_keys(n: int, unmatched: int, tokens: np.ndarray) -> np.ndarray:
    """Keys of a set of n tokens, of which ``unmatched`` occur nowhere else; tokens: its other ones (short form)."""
    out = []
    place, ident = allocation()[(tokens & U64(CLASSES - 1)).astype(np.int64)], mix(tokens >> U64(4))
    for upper, most in bands(n):
        need = most + 1 - unmatched
        if need <= 0:
            continue
        fine = upper <= 128
        slots = np.where(place == CLASSES, U64(1 << 40 if fine else upper // COARSE), U64(1 << 40 if fine else 8 * upper))
        seg = (mix(ident + U64(upper)) >> U64(20)) % slots + (place.astype(U64) << U64(56))
        order = np.argsort(seg, kind="stable")
        s, v = seg[order], ident[order]
        first = np.flatnonzero(np.concatenate(([True], s[1:] != s[:-1]))) if len(s) else np.zeros(0, np.int64)
        size = np.diff(np.append(first, len(s)))
        double = (size > 1) & (s[first] >> U64(56) == CLASSES)
        total = np.cumsum(1 + double)
        if not len(total) or total[-1] < need:
            raise RuntimeError(f"segments of a set of {n} tokens allow {total[-1] if len(total) else 0}, {need} are needed")
        take = int(np.searchsorted(total, need)) + 1
        whole = np.add.reduceat(v, first)[:take]
        salt = mix(s[first[:take]] + U64(upper * 0x9E3779B97F4A7C15 & (1 << 64) - 1))
        out.append(mix(whole + salt))
        end = first[take] if take < len(first) else len(s)
        inside = np.repeat(np.arange(take), size[:take])
        d = double[:take][inside]
        out.append(mix(whole[inside[d]] - v[:end][d] + salt[inside[d]]))
    return np.unique(np.concatenate(out)) if out else np.zeros(0, U64)


def _star(key: np.ndarray, fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(one entry per key with its smallest fp, distinct edges from other fps to that one)."""
    order = np.lexsort((fp, key))
    key, fp = key[order], fp[order]
    first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1]))) if len(key) else np.zeros(0, np.int64)
    low = np.repeat(fp[first], np.diff(np.append(first, len(key))))
    ends = np.empty(len(first), _PAIR)
    ends["a"], ends["b"] = key[first], fp[first]
    k = low != fp
    edges = np.empty(int(k.sum()), _PAIR)
    edges["a"], edges["b"] = low[k], fp[k]
    return ends, np.unique(edges)


def _allocate(parts: int):
    """Keys of sets that may have a partner, joined within the task.  Registry rows pass through."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, sizes = [], {}
        for batch in batches:
            kind = batch.column(0).to_numpy()
            registry = batch.filter(pa.array(kind == REGISTRY))
            if registry.num_rows:
                yield registry
            sized = batch.filter(pa.array(kind == SIZES))
            sizes.update(zip(sized.column(4).to_pylist(), sized.column(3).to_pylist()))
            found += [np.frombuffer(x.as_buffer(), _ENTRY) for x in batch.filter(pa.array(kind == MATCHED)).column(5)]
        if not found:
            return
        e = np.unique(np.concatenate(found))  # a set met by several tasks may have sent a token twice
        fp, key = np.ascontiguousarray(e["fp"]), np.ascontiguousarray(e["key"])
        first = np.flatnonzero(np.concatenate(([True], fp[1:] != fp[:-1])))
        n = np.array([sizes[x] for x in fp[first].view(np.int64).tolist()])
        count = np.diff(np.append(first, len(fp)))
        shared = np.minimum(n, count + (n > 128))  # two tokens of a large set may look alike here
        keys, owners = [], []
        for i in np.flatnonzero(4 * shared >= 3 * n):
            a = first[i]
            k = segment_keys(int(n[i]), int(n[i] - shared[i]), key[a : a + count[i]])
            keys.append(k)
            owners.append(np.full(len(k), fp[a], U64))
        if keys:
            ends, edges = _star(np.concatenate(keys), np.concatenate(owners))
            out = _by_part(KEYS, _part(ends["a"], parts), ends)
            out += [(EDGES, 0, None, None, None, edges[i : i + 65536].tobytes()) for i in range(0, len(edges), 65536)]
            yield _rows(out)

    return run


def _edge_batch(edges: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(edges[c]).view(np.int64)) for c in "ab"], ["a", "b"])


def _join_keys(parts: int):
    """Edges of all keys, packed by their first end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, edges = [], []
        for batch in batches:
            for kind, x in zip(batch.column(0).to_pylist(), batch.column(5)):
                (edges if kind == EDGES else keys).append(np.frombuffer(x.as_buffer(), _PAIR))
        if keys:
            e = np.concatenate(keys)
            edges.append(_star(np.ascontiguousarray(e["a"]), np.ascontiguousarray(e["b"]))[1])
        if edges:
            e = np.unique(np.concatenate(edges))
            if len(e):
                yield _rows(_by_part(EDGES, _part(e["a"], parts), e))

    return run


def _distinct_edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    found = [np.frombuffer(x.as_buffer(), _PAIR) for batch in batches for x in batch.column(5)]
    if found:
        yield _edge_batch(np.unique(np.concatenate(found)))


def linked(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Boolean matrix: 100 * |intersection| >= 75 * |union|, for all pairs of two lists of sorted sets."""
    nl, nr = np.array([len(x) for x in left]), np.array([len(x) for x in right])
    if len(left) * len(right) <= 64:
        both = np.array([[len(np.intersect1d(x, y, assume_unique=True)) for y in right] for x in left])
    else:
        tok = np.concatenate([*left, *right])
        row = np.repeat(np.arange(len(left) + len(right)), np.concatenate((nl, nr)))
        vocab, inv, count = np.unique(tok, return_inverse=True, return_counts=True)
        keep = count[inv] > 1
        slot = np.cumsum(count > 1) - 1
        col, row = slot[inv[keep]], row[keep]
        order = np.argsort(col, kind="stable")
        col, row = col[order], row[order]
        both = np.zeros((len(left), len(right)), np.float32)
        wide = 4096
        for c in range(0, int(col[-1]) + 1 if len(col) else 0, wide):
            a, b = np.searchsorted(col, (c, c + wide))
            m = np.zeros((len(left) + len(right), wide), np.float32)
            m[row[a:b], col[a:b] - c] = 1
            both += m[: len(left)] @ m[len(left) :].T
        both = both.astype(np.int64)
    return 100 * both >= 75 * (nl[:, None] + nr[None, :] - both)


def spanning(sets: list[np.ndarray], other: list[np.ndarray] | None = None) -> list[tuple[int, int]]:
    """A spanning forest of the links among sets, or between sets and other (numbered after them)."""
    link = linked(sets, sets if other is None else other)
    size = len(sets) + (len(other) if other is not None else 0)
    if other is not None:
        full = np.zeros((size, size), bool)
        full[: len(sets), len(sets) :] = link
        full[len(sets) :, : len(sets)] = link.T
        link = full
    todo, out = np.ones(size, bool), []
    for r in range(size):
        if not todo[r]:
            continue
        todo[r], queue = False, [r]
        while queue:
            x = queue.pop()
            near = np.flatnonzero(link[x] & todo)
            todo[near] = False
            out += [(x, int(y)) for y in near]
            queue += near.tolist()
    return out


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All true links inside each task's (pair of) blocks, as spanning forests."""
    tasks: dict[tuple, dict] = {}
    for batch in batches:
        for cluster, i, j, side, fp, tokens in zip(*(c.to_pylist() for c in batch.columns)):
            tasks.setdefault((cluster, i, j), ({}, {}))[side][fp] = np.frombuffer(tokens, "<u8")
    for (_, i, j), (left, right) in tasks.items():
        names = [*left, *right]
        pairs = spanning(list(left.values()), list(right.values()) if i != j else None) if left and (right or i == j) else []
        if pairs:
            yield pa.RecordBatch.from_arrays([pa.array([names[x] for x, _ in pairs], pa.int64()), pa.array([names[y] for _, y in pairs], pa.int64())], ["a", "b"])


def _blocked(fp: str, blocks: str) -> F.Column:
    return F.pmod(F.xxhash64(F.lit(3), F.col(fp)), F.col(blocks)).cast("int")


def _star_tasks(stars: DataFrame) -> DataFrame:
    """Each candidate against the smallest one it is joined to: (cluster, i, j, side, fp); many candidates of one leader are several tasks."""
    sizes = stored(stars.groupBy("cluster").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks")), "sizes")
    mine = stars.join(sizes, "cluster").select("cluster", _blocked("fp", "blocks").alias("i"), F.lit(-1).alias("j"), F.lit(1).alias("side"), "fp")
    lead = sizes.select("cluster", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("i"), F.lit(-1).alias("j"), F.lit(0).alias("side"), F.col("cluster").alias("fp"))
    return mine.unionByName(lead)


def _stray_tasks(parted: DataFrame) -> DataFrame:
    """What (node, component, part) leaves to compare: in each component of candidates the greatest part is the core, known to hang
    together; all others, the strays, meet each other and the core, as pairs of blocks.  Core sets never meet."""
    sizes = parted.groupBy("component", "part").agg(F.count("*").alias("n"))
    core = sizes.groupBy("component").agg(F.min(F.struct((-F.col("n")).alias("less"), "part")).alias("top"), F.sum("n").alias("all"))
    core = core.select("component", F.col("top.part").alias("core"), F.ceil((F.col("all") + F.col("top.less")) / BLOCK).cast("int").alias("strays"), F.ceil(-F.col("top.less") / BLOCK).cast("int").alias("cores"))
    left = parted.join(stored(core.where("strays > 0"), "cores"), "component")
    inner = left.where("part = core").withColumn("i", F.explode(F.sequence(F.lit(0), F.col("strays") - 1)))
    inner = inner.select(F.col("component").alias("cluster"), "i", (F.col("strays") + _blocked("node", "cores")).alias("j"), F.lit(1).alias("side"), F.col("node").alias("fp"))
    outer = left.where("part <> core").withColumn("mine", _blocked("node", "strays")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("strays") + F.col("cores") - 1)))
    outer = outer.select(F.col("component").alias("cluster"), F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), F.when(F.col("mine") <= F.col("other"), 0).otherwise(1).alias("side"), F.col("node").alias("fp"))
    return inner.unionByName(outer)


def classes(docs: DataFrame, w: int = W, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id: one row per row of docs."""
    return _classes(docs, w, id_col, text_col).drop("th")


def _classes(docs: DataFrame, w: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """classes, with the hash of each row's text."""
    spark = docs.sparkSession
    parts = partitions(spark, docs)
    docs = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"), F.xxhash64(docs[text_col]).alias("th"))
    sent = docs.mapInArrow(lean(_emit(w, parts)), ROW).repartitionById(parts, F.col("part"))
    matched = sent.mapInArrow(lean(_match(parts)), ROW).repartitionById(parts, F.col("part"))
    state = stored(matched.mapInArrow(lean(_allocate(parts)), ROW), "sets")
    registry = state.where(f"kind = {REGISTRY}").select("doc_id", "th", "n", "fp")
    edges = state.where(f"kind in ({KEYS}, {EDGES})").repartitionById(parts, F.col("part")).mapInArrow(lean(_join_keys(parts)), ROW)
    edges = edges.repartitionById(parts, F.col("part")).mapInArrow(lean(_distinct_edges), "a long, b long")
    edges = stored(edges, "candidates")
    clusters = stored(components(edges), "clusters")
    first = registry.where("n > 0").groupBy("fp").agg(F.min(F.struct("doc_id", "th")).alias("one"))
    members = clusters.join(first, clusters["node"] == first["fp"]).select(F.col("one.doc_id").alias("d"), F.col("one.th").alias("t"), "fp")

    def sets(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for lo, hi, buf, off in text_slices(batch, "text"):
            s = pa.array([x.tobytes() for x in shingle_sets(buf, off, w)], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(1).slice(lo, hi - lo), s], ["fp", "tokens"])

    # two rows of one id and text are one set
    tokens = stored(map_batches(docs.join(members, same_row()).select("text", "fp"), sets, "fp long, tokens binary").dropDuplicates(["fp"]), "tokens")

    def links(tasks: DataFrame) -> DataFrame:
        """True links inside tasks (cluster, i, j, side, fp)."""
        given = tasks.join(tokens, "fp").select("cluster", "i", "j", "side", "fp", "tokens")
        return stored(given.repartition(parts, "cluster", "i", "j").mapInArrow(lean(_verify), "a long, b long"), "links")

    stars = stored(edges.groupBy(F.col("b").alias("fp")).agg(F.min("a").alias("cluster")), "stars")
    near = links(_star_tasks(stars))
    parted = stored(clusters.join(components(near).select(F.col("node").alias("fp"), F.col("component").alias("part")), F.col("node") == F.col("fp"), "left").select("node", "component", F.coalesce("part", "node").alias("part")), "parted")
    rest = links(_stray_tasks(parted))
    joined = components(near.unionByName(rest))
    named = stored(registry.join(joined, registry["fp"] == joined["node"], "left").select("doc_id", "th", "n", F.coalesce("component", "fp").alias("class")), "named")
    # stored, so that Spark can split the class that a third of all rows may be in
    least = stored(named.groupBy("class").agg(F.min("doc_id").alias("component_id"), F.count("*").alias("many")).where("many > 1").select("class", "component_id"), "least")
    out = named.join(least, "class", "left")
    alone = (F.col("n") == 0) | F.col("component_id").isNull()
    return out.select("doc_id", "th", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNull(), F.lit(None)).when(alone, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def representatives(docs: DataFrame, w: int = W) -> DataFrame:
    """The rows of docs, all columns, but those whose class has a smaller doc_id.  Rows without an id stay."""
    drop = _classes(docs, w).where("component_id < doc_id").select("doc_id", "th").distinct()
    return docs.join(drop, (docs["doc_id"].cast("long") == drop["doc_id"]) & (F.xxhash64(docs["text"]) == drop["th"]), "left_anti")
