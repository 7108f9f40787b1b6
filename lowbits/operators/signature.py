"""Full-width minwise signatures: k minima per set."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import hashing
from ..sources.io import stored

CHUNK = 64  # minima per aggregate: keeps generated code within one method's size


def build_full(sets: DataFrame, kind: str = "affine31", k: int = 64, seed: int = 0, universe: DataFrame | None = None) -> DataFrame:
    """(set_id, f, z): one wide aggregate per chunk, partial sums on the map side, no explode of sets by permutation.

    kind perm: ranks come from a join with the (elem, k ranks) table of the universe (the sets' own elements by default)."""
    chunks = [(lo, min(lo + CHUNK, k)) for lo in range(0, k, CHUNK)]
    if kind == "perm":
        ranks = hashing.permutations(sets if universe is None else universe, k, seed)
        listed = ranks.groupBy("elem").agg(F.array_sort(F.collect_list(F.struct("j", "rank"))).alias("m"))  # k entries
        wide = listed.select("elem", *(F.transform(F.slice("m", lo + 1, hi - lo), lambda x: x["rank"]).alias(f"r{lo}") for lo, hi in chunks))
        source = sets.join(stored(wide, "ranks") if len(chunks) > 1 else wide, "elem")
        column = lambda j: F.col(f"r{j // CHUNK * CHUNK}")[j % CHUNK]
    else:
        source, hashes = sets, hashing.family(kind, k, seed)
        column = hashes.__getitem__
    parts = []
    for lo, hi in chunks:
        aggs = [F.min(column(j)).alias(f"z{j}") for j in range(lo, hi)]
        parts.append(source.groupBy("set_id").agg(*([F.count("*").alias("f")] if lo == 0 else []), *aggs))
    out = parts[0]
    for p in parts[1:]:
        out = out.join(p, "set_id")
    return out.select("set_id", "f", F.array(*(F.col(f"z{j}") for j in range(k))).alias("z"))


def build_narrow(sets: DataFrame, kind: str = "affine31", k: int = 64, seed: int = 0) -> DataFrame:
    """(set_id, j, z) by exploding permutations: the plain way, for comparison and for very many permutations."""
    if kind == "perm":
        return sets.join(hashing.permutations(sets, k, seed), "elem").groupBy("set_id", "j").agg(F.min("rank").alias("z"))
    hashed = sets.select("set_id", F.posexplode(F.array(*hashing.family(kind, k, seed))).alias("j", "h"))
    return hashed.groupBy("set_id", "j").agg(F.min("h").alias("z"))


AT_ONCE = 1 << 15  # elements permuted together


def nested(df: DataFrame, id_col: str, elems_col: str, k: int = 64, seed: int = 0, kind: str = "affine31", kept: str | None = None) -> DataFrame:
    """(set_id, f, z) of sets that are array columns: an Arrow kernel per batch, no shuffle.  Repeats in an array don't count; null and empty arrays give no row.

    kept: a type as which the elements of each set, in order, are kept as the column elems."""
    of_kept = [pa.list_(pa.from_numpy_dtype({"int": np.int32, "bigint": np.int64}[kept]))] if kept else []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, x = members(b.column(1))
            if not len(x):
                continue
            first = np.flatnonzero(np.r_[True, rows[1:] != rows[:-1]])
            f, n = np.diff(np.r_[first, len(x)]), len(first)
            z = pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * k, k, dtype=np.int32)), pa.array(minima(x, first, k, seed, kind).ravel()))
            held = [pa.ListArray.from_arrays(pa.array(np.r_[first, len(x)].astype(np.int32)), pa.array(x.astype(t.value_type.to_pandas_dtype()))) for t in of_kept]
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(rows[first])), pa.array(f), z, *held], ["set_id", "f", "z", *(["elems"] if kept else [])])

    kind_of = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, F.col(elems_col).cast("array<bigint>")).mapInArrow(run, f"set_id {kind_of}, f bigint, z array<bigint>" + (f", elems array<{kept}>" if kept else ""))


def members(lists: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(row, element) of arrays, each pair once and in order; nulls left out."""
    rows, x = pc.list_parent_indices(lists), lists.flatten()
    if x.null_count:
        rows, x = rows.filter(pc.is_valid(x)), x.drop_null()
    rows, x = rows.to_numpy().astype(np.int64), x.to_numpy()
    if len(x) and x.min() >= 0 and x.max() <= hashing.PRIME:
        both = np.sort(rows << 31 | x)
        both = both[np.r_[True, both[1:] != both[:-1]]]
        return both >> 31, both & hashing.PRIME
    order = np.lexsort((x, rows))
    rows, x = rows[order], x[order]
    once = np.r_[True, (rows[1:] != rows[:-1]) | (x[1:] != x[:-1])] if len(x) else np.zeros(0, bool)
    return rows[once], x[once]


def minima(x: np.ndarray, first: np.ndarray, k: int, seed: int, kind: str) -> np.ndarray:
    """Matrix (sets, k) of minima of the sets x[first[i] : first[i + 1]]."""
    out = np.empty((len(first), k), np.int64)
    ends, lo = np.r_[first, len(x)], 0
    while lo < len(first):
        hi = max(lo + 1, int(np.searchsorted(ends, ends[lo] + AT_ONCE, "right")) - 1)
        own, at = x[ends[lo] : ends[hi]], ends[lo:hi] - ends[lo]
        if kind == "bijective":
            for j in range(k):
                out[lo:hi, j] = np.minimum.reduceat(hashing.bijective(own, j, seed), at)
        elif own.min() >= 0 and own.max() < hashing.PRIME:
            own, p = own.astype(np.uint64), np.uint64(hashing.PRIME)
            for j, (a, c) in enumerate(hashing.coefficients(k, seed)):
                v = own * np.uint64(a) + np.uint64(c)
                v = (v & p) + (v >> np.uint64(31))  # modulo 2^31 - 1, but for one subtraction
                out[lo:hi, j] = np.minimum.reduceat(np.minimum(v, v - p), at)
        else:
            for j, (a, c) in enumerate(hashing.coefficients(k, seed)):
                out[lo:hi, j] = np.minimum.reduceat((a * own + c) % hashing.PRIME, at)
        lo = hi
    return out


def narrow(full: DataFrame) -> DataFrame:
    return full.select("set_id", F.posexplode("z").alias("j", "z"))


def merge(a: DataFrame, b: DataFrame, disjoint: bool = False) -> DataFrame:
    """Signatures of unions: element-wise minima of full-width signatures.

    f, the size of the union, is the sum where the caller knows the sets to be disjoint; sizes of overlapping sets don't add up, so it is null."""
    both = a.unionByName(b).select("set_id", "f", F.posexplode("z").alias("j", "z")).groupBy("set_id", "j").agg(F.min("z").alias("z"), F.sum("f").alias("f"))
    f = F.max("f") if disjoint else F.lit(None).cast("long")
    return both.groupBy("set_id").agg(f.alias("f"), F.transform(F.array_sort(F.collect_list(F.struct("j", "z"))), lambda x: x["z"]).alias("z"))
