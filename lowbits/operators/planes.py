"""Bit planes: bit i of all k samples side by side, 64 to a word, so a table serves every b by column pruning."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def words(k: int) -> int:
    return -(-k // 64)


def _word(z: str, lo: int, hi: int, bit: int) -> Column:
    """The word of samples lo..hi-1 at the given bit, unrolled so that it stays in generated code."""
    out = None
    for j in range(lo, hi):
        x = F.shiftleft(F.shiftright(F.col(z)[j], bit).bitwiseAND(F.lit(1).cast("long")), j - lo)
        out = x if out is None else out.bitwiseOR(x)
    return out


def from_full(full: DataFrame, k: int, b_max: int = 1, kept: tuple[str, ...] = ()) -> DataFrame:
    """(set_id, f, plane_0 .. plane_{b_max-1}), each an array of words, and with few planes the columns kept.  Few planes are generated code; many would
    unroll beyond one method's size and are packed in Arrow batches."""
    if b_max <= 4:
        return full.select("set_id", "f", *(F.array(*(_word("z", w * 64, min(k, w * 64 + 64), i) for w in range(words(k)))).alias(f"plane_{i}") for i in range(b_max)), *kept)
    kind, n = full.schema["set_id"].dataType.simpleString(), words(k)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.num_rows
            if not rows:
                continue
            z = np.zeros((rows, 64 * n), np.int64)
            z[:, :k] = batch.column(2).flatten().to_numpy().reshape(rows, -1)[:, :k]
            cut = pa.array(np.arange(0, (rows + 1) * n, n, dtype=np.int32))
            planes = [pa.ListArray.from_arrays(cut, pa.array(np.packbits((z >> i & 1).astype(bool), axis=1, bitorder="little").view("<i8").ravel())) for i in range(b_max)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *planes], ["set_id", "f", *(f"plane_{i}" for i in range(b_max))])

    schema = f"set_id {kind}, f long, " + ", ".join(f"plane_{i} array<long>" for i in range(b_max))
    return full.select("set_id", F.col("f").cast("long"), "z").mapInArrow(pack, schema)


def fold(planes: DataFrame, k: int, m: int = 2) -> DataFrame:
    """(set_id, f, fold): k bits, each the XOR of the lowest bits of m permutations (j, j + k, ...).  k is a multiple of 64."""
    if k % 64:
        raise ValueError("k must be a multiple of 64")
    n = words(k)

    def one(w: int) -> Column:
        out = F.col("plane_0")[w]
        for t in range(1, m):
            out = out.bitwiseXOR(F.col("plane_0")[w + t * n])
        return out

    return planes.select("set_id", "f", F.array(*(one(w) for w in range(n))).alias("fold"))


def long_form(planes: DataFrame, columns: list[str]) -> DataFrame:
    """(set_id, plane, word_no, word)."""

    def rows_of(i: int, c: str) -> Column:
        return F.transform(F.col(c), lambda x, w: F.struct(F.lit(i).alias("plane"), w.alias("word_no"), x.alias("word")))

    rows = [rows_of(i, c) for i, c in enumerate(columns)]
    return planes.select("set_id", F.explode(F.concat(*rows)).alias("x")).select("set_id", "x.plane", "x.word_no", "x.word")
