"""Packed sign planes: layout, dot products, norms and cosines as expressions.

A ladder code of ``planes`` planes and ``n`` bits is stored as one BIGINT column
per plane and 64-bit word, ``p{plane}_w{word}``; bit i of a word is dimension i of
that word, set for +1.  Plane t counts 2^-t, or 1 in an unweighted code.
Everything here is plain column algebra, so it stays inside generated code.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

MAX_DEPTH = 8


@dataclass(frozen=True)
class CodeSpec:
    """Shape of a code: bits, planes (residual planes + 1), weights, model."""

    n: int = 64
    planes: int = 2
    weighted: bool = True
    model: str = ""

    def __post_init__(self):
        if self.n % 64 or self.n < 64:
            raise ValueError("n must be a multiple of 64")
        if not 1 <= self.planes <= MAX_DEPTH + 1:
            raise ValueError(f"1 to {MAX_DEPTH + 1} planes")

    @property
    def words(self) -> int:
        return self.n // 64

    @property
    def depth(self) -> int:
        return self.planes - 1

    @property
    def bits(self) -> int:
        """Bits per dimension."""
        return self.planes

    @property
    def bytes_per_row(self) -> int:
        return self.n * self.planes // 8

    def columns(self, prefix: str = "") -> list[str]:
        return [f"{prefix}p{p}_w{w}" for p in range(self.planes) for w in range(self.words)]

    def schema(self, key: str = "keyword_id", norm: bool = True) -> StructType:
        fields = [StructField(key, LongType(), False), *[StructField(c, LongType(), False) for c in self.columns()]]
        return StructType([*fields, *([StructField("norm_sq", IntegerType(), False)] if norm else [])])

    def weight(self, plane: int) -> int:
        """Integer weight: 2^(depth - plane), or 1 without weights."""
        return 1 << (self.depth - plane) if self.weighted else 1

    @property
    def scale(self) -> int:
        """What integer weights are multiplied with: code * scale is whole."""
        return 1 << self.depth if self.weighted else 1

    def matches(self, other: CodeSpec) -> bool:
        return self.n == other.n and self.model == other.model


def pm_dot(x: Column, y: Column, n: int = 64) -> Column:
    """Dot product of two ±1 words of ``n`` bits: n less twice the differing bits."""
    return F.lit(n) - F.shiftleft(F.bit_count(x.bitwiseXOR(y)), 1)


def plane_dot(q: str, i: int, k: str, j: int, words: int) -> Column:
    out = pm_dot(F.col(f"{q}p{i}_w0"), F.col(f"{k}p{j}_w0"))
    for w in range(1, words):
        out = out + pm_dot(F.col(f"{q}p{i}_w{w}"), F.col(f"{k}p{j}_w{w}"))
    return out


def dot_expr(qspec: CodeSpec, kspec: CodeSpec, q: str = "q_", k: str = "", order: str = "horner") -> Column:
    """Scaled integer dot product of two codes.

    ``naive`` multiplies each plane pair by its weight.  ``horner`` adds the pairs
    of one total exponent and shifts the running sum left once per exponent: at
    most ``u + v`` shifts.
    """
    if qspec.n != kspec.n:
        raise ValueError("codes of different length")
    pairs = [(i, j) for i in range(qspec.planes) for j in range(kspec.planes)]
    if order == "naive" or not (qspec.weighted and kspec.weighted):
        terms = [plane_dot(q, i, k, j, qspec.words) * F.lit(qspec.weight(i) * kspec.weight(j)) for i, j in pairs]
        out = terms[0]
        for t in terms[1:]:
            out = out + t
        return out
    out = None
    for exponent in range(qspec.depth + kspec.depth + 1):
        for i, j in pairs:
            if i + j == exponent:
                dot = plane_dot(q, i, k, j, qspec.words)
                out = dot if out is None else (F.shiftleft(out, 1) if first else out) + dot
                first = False
        first = True
    return out


def norm_sq_expr(spec: CodeSpec, prefix: str = "") -> Column:
    """Squared norm of the scaled code, from its planes only.

    n times the squared weights, plus twice the weighted dots of plane pairs.
    """
    out = F.lit(spec.n * sum(spec.weight(i) ** 2 for i in range(spec.planes)))
    for i in range(spec.planes):
        for j in range(i + 1, spec.planes):
            out = out + plane_dot(prefix, i, prefix, j, spec.words) * F.lit(2 * spec.weight(i) * spec.weight(j))
    return out.cast("int")


def rank_expr(dot: Column, k_norm_sq: Column) -> Column:
    """Score that ranks keywords of one query: the query's norm is left out."""
    return dot / F.sqrt(F.when(k_norm_sq > 0, k_norm_sq.cast("double")))


def cosine_expr(dot: Column, q_norm_sq: Column, k_norm_sq: Column) -> Column:
    """Full cosine, comparable across queries; null for a zero code."""
    product = q_norm_sq.cast("double") * k_norm_sq.cast("double")
    return dot / F.sqrt(F.when(product > 0, product))


def shift_count(u: int, v: int, order: str = "horner") -> int:
    """Shifts for one pair of codes."""
    return u + v if order == "horner" else sum(1 for i in range(u + 1) for j in range(v + 1) if i + j < u + v)


def pack(planes: np.ndarray) -> np.ndarray:
    """±1 (rows x n) to int64 words (rows x n/64)."""
    bits = (np.asarray(planes) > 0).astype(np.uint8)
    return np.packbits(bits, axis=1, bitorder="little").view("<i8")


def unpack(words: np.ndarray, n: int) -> np.ndarray:
    """int64 words (rows x n/64) to ±1 (rows x n) as int8."""
    raw = np.ascontiguousarray(words, dtype="<i8").view(np.uint8)
    return (np.unpackbits(raw, axis=1, bitorder="little", count=n).astype(np.int8) * 2 - 1).astype(np.int8)


def pack_expr(signs: Column) -> Column:
    """An array of up to 64 ±1 values as a BIGINT, in SQL only."""
    return F.aggregate(F.reverse(signs), F.lit(0).cast("long"), lambda acc, s: F.shiftleft(acc, 1).bitwiseOR(F.when(s > 0, F.lit(1)).otherwise(F.lit(0)).cast("long")))


def unpack_expr(word: Column, n: int = 64) -> Column:
    """A BIGINT as an array of ±1 integers."""
    return F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.when(F.getbit(word, i) == 1, F.lit(1)).otherwise(F.lit(-1)))


def plus_times(w: float):
    """(a, b) to a + w b, as a lambda of exactly two arguments."""
    return lambda a, b: a + b * F.lit(w)


def dense_expr(spec: CodeSpec, prefix: str = "") -> Column:
    """The code as an array of doubles, for looking at (one word per plane)."""
    if spec.words != 1:
        raise ValueError("dense view of 64-bit codes only")
    out = F.transform(unpack_expr(F.col(f"{prefix}p0_w0"), spec.n), lambda x: x.cast("double"))
    for t in range(1, spec.planes):
        w = 2.0**-t if spec.weighted else 1.0
        out = F.zip_with(out, unpack_expr(F.col(f"{prefix}p{t}_w0"), spec.n), plus_times(w))
    return out
