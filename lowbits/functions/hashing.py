"""Hash families as Column expressions.

kinds
  affine31   (a x + c) mod 2^31 - 1 of premixed 31-bit ids; portable to any SQL engine
  mix64      xxhash64(elem, seed_j), shifted to 63 bits
  md5        first 60 bits of md5(seed:j:elem); wide and portable to any SQL engine, at the price of a digest per value
  perm       true random permutation of a finite universe: rank of md5(j:elem)
  bijective  invertible 62-bit mixing rounds, in Arrow batches (see signature.nested)
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


def md5_int(text: str, digits: int = 15) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:digits], 16)


def md5_long(c: Column) -> Column:
    """First 15 hex digits of md5 as BIGINT."""
    return F.conv(F.substring(F.md5(c.cast("string")), 1, 15), 16, 10).cast("long")


def to_domain(c: Column, bits: int = 31) -> Column:
    """Hash to a universe: 31, 40 or 60 bits (md5, portable), or 63 bits (xxhash64)."""
    if bits == 31:
        return F.pmod(md5_long(c), F.lit(PRIME)).cast("long")
    if bits in (40, 60):
        return md5_long(c).bitwiseAND(F.lit((1 << bits) - 1))
    if bits == 63:
        return F.xxhash64(c).bitwiseAND(F.lit((1 << bits) - 1))
    raise ValueError(bits)


def coefficients(k: int, seed: int = 0) -> list[tuple[int, int]]:
    """(a, c) of k affine permutations."""
    return [(1 + md5_int(f"a{seed}:{j}") % (PRIME - 1), md5_int(f"c{seed}:{j}") % PRIME) for j in range(k)]


def family(kind: str, k: int, seed: int = 0, elem: str = "elem") -> list[Column]:
    """k permuted values of the column elem."""
    x = F.col(elem)
    if kind == "affine31":
        return [F.pmod(F.lit(a) * x + F.lit(c), F.lit(PRIME)) for a, c in coefficients(k, seed)]
    if kind == "mix64":
        return [F.shiftrightunsigned(F.xxhash64(x, F.lit(md5_int(f"m{seed}:{j}"))), 1) for j in range(k)]
    if kind == "md5":
        return [md5_long(F.concat(F.lit(f"{seed}:{j}:"), x.cast("string"))) for j in range(k)]
    raise ValueError(kind)


def domain_size(kind: str, universe: int | None = None) -> float:
    """Size of the permuted values' range: densities must refer to it."""
    return {"affine31": float(PRIME), "mix64": 2.0**63, "md5": 2.0**60, "bijective": 2.0**62, "perm": float(universe or 0)}[kind]


#: Elements of one permutation that a sort holds; larger universes are ranked in so many ranges of the key.
RANGE = 100_000


def permutations(universe: DataFrame, k: int, seed: int = 0, elem: str = "elem") -> DataFrame:
    """(elem, j, rank): k true permutations of a finite universe, by the order of md5(seed:j:elem).

    The first hex digits of the key cut each permutation into ranges of about ``RANGE`` elements: ranks inside a
    range plus the sizes of those before it, so no task sorts a whole universe."""
    spark = universe.sparkSession
    own = universe.select(elem).distinct()
    digits = max(0, math.ceil(math.log(max(1, own.count() / RANGE), 16)))
    each = own.crossJoin(F.broadcast(spark.range(k).select(F.col("id").cast("int").alias("j"))))
    keyed = each.withColumn("key", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("j").cast("string"), F.col(elem).cast("string"))))
    keyed = keyed.withColumn("range", F.substring("key", 1, digits))
    place = F.row_number().over(Window.partitionBy("j", "range").orderBy("key", elem)) - 1
    if not digits:
        return keyed.select(elem, "j", place.cast("long").alias("rank"))
    sizes = keyed.groupBy("j", "range").agg(F.count("*").alias("n"))  # at most 16 ** digits rows for each j
    before = F.coalesce(F.sum("n").over(Window.partitionBy("j").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = sizes.select("j", "range", before.alias("start"))
    return keyed.withColumn("place", place).join(starts, ["j", "range"]).select(elem, "j", (F.col("place") + F.col("start")).cast("long").alias("rank"))


_TURNS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(math.sin(i + 1)) * 2**32) & 0xFFFFFFFF for i in range(64)]
_AT = [[i, (5 * i + 1) % 16, (3 * i + 5) % 16, 7 * i % 16] for i in range(64)]
AT_ONCE = 1 << 15  # texts digested together


class Texts:
    """Elements as text, digested together: keys(prefix) are the first 64 bits of md5(prefix + text), in the order of its hex digits.

    Two elements of one permutation share a key with a probability of 2^-64; they then take the same place."""

    def __init__(self, texts: list[str]):
        raw = [t.encode() for t in texts]
        self.n, by_length = len(raw), {}
        for i, t in enumerate(raw):
            by_length.setdefault(len(t), []).append(i)
        self.parts = []
        for length, at in by_length.items():
            for lo in range(0, len(at), AT_ONCE):
                own = at[lo : lo + AT_ONCE]
                body = np.frombuffer(b"".join(raw[i] for i in own), np.uint8).reshape(len(own), length)
                self.parts.append((np.array(own), body, [raw[i] for i in own]))

    def keys(self, prefix: str) -> np.ndarray:
        out, head = np.empty(self.n, np.uint64), prefix.encode()
        for own, body, raw in self.parts:
            fits = len(head) + body.shape[1] <= 55
            out[own] = _digests(head, body) if fits else [int.from_bytes(hashlib.md5(head + t).digest()[:8], "big") for t in raw]
        return out


def _digests(head: bytes, body: np.ndarray) -> np.ndarray:
    """First 64 bits of md5(head + row) of every row; one block of 64 bytes each."""
    n, size = len(body), len(head) + body.shape[1]
    used = size // 4 + 1
    text = np.zeros((n, 4 * used), np.uint8)
    text[:, : len(head)] = np.frombuffer(head, np.uint8)
    text[:, len(head) : size] = body
    text[:, size] = 0x80
    words = [*np.ascontiguousarray(text.view("<u4").T), *([0] * (16 - used))]
    words[14] = words[14] + 8 * size if used > 14 else 8 * size
    start = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
    a, b, c, d = (np.full(n, x, np.uint32) for x in start)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        kind = i // 16
        if kind == 0:  # d ^ (b & (c ^ d))
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif kind == 1:  # c ^ (d & (b ^ c))
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif kind == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.bitwise_not(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        w = words[_AT[i][kind]]
        np.add(f, a, out=f)
        if isinstance(w, int):
            np.add(f, np.uint32((_SINES[i] + w) & 0xFFFFFFFF), out=f)
        else:
            np.add(f, w, out=f)
            np.add(f, np.uint32(_SINES[i]), out=f)
        turn = _TURNS[kind][i % 4]
        np.left_shift(f, np.uint32(turn), out=t)
        np.right_shift(f, np.uint32(32 - turn), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=f)
        a, d, c, b, f = d, c, b, f, a
    first, second = ((x + np.uint32(s)).byteswap().astype(np.uint64) for x, s in ((a, start[0]), (b, start[1])))
    return (first << np.uint64(32)) | second


def bijective(x: np.ndarray, j: int, seed: int = 0) -> np.ndarray:
    """An invertible mixing of 62-bit values: odd multiplications and xor-shifts modulo 2^62."""
    mask = np.uint64((1 << 62) - 1)
    v = (x.astype(np.uint64) ^ np.uint64(md5_int(f"b{seed}:{j}"))) & mask
    for t in range(3):
        v = (v * np.uint64(md5_int(f"b{seed}:{j}:{t}") | 1)) & mask
        v ^= v >> np.uint64(29)
    return v
