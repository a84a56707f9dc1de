"""Vector expressions from built-in functions; the forms the SQL oracles share."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def l2sq(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(l2sq(a, b))


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x * y))


def norm(a: Column) -> Column:
    return F.sqrt(_sum(F.transform(a, lambda x: x * x)))


def cosine(a: Column, b: Column) -> Column:
    """Null where a vector is all zero."""
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def normalize(a: Column) -> Column:
    return F.transform(a, lambda x: F.try_divide(x, norm(a)))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def scale(a: Column, s: float | Column) -> Column:
    return F.transform(a, lambda x: x * s)


def part(a: Column, start: int | Column, length: int | Column) -> Column:
    """Slice from 0-based `start`."""
    begin = F.lit(start + 1) if isinstance(start, int) else start + 1
    return F.slice(a, begin, F.lit(length) if isinstance(length, int) else length)


def partial_l2sq(a: Column, b: Column, t: int) -> Column:
    """Squared distance over the first t dimensions."""
    return l2sq(part(a, 0, t), part(b, 0, t))


def sign_words(a: Column, dim: int) -> Column:
    """Sign bits packed into longs, first dimension in the lowest bit; values >= 0 give 1."""
    words = []
    for start in range(0, dim, 64):
        bits = [F.when(F.element_at(a, j + 1) >= 0, F.lit(1 << (j - start) if j - start < 63 else -(1 << 63)).cast("long")).otherwise(F.lit(0).cast("long")) for j in range(start, min(dim, start + 64))]
        words.append(reduce(lambda x, y: x.bitwiseOR(y), bits))
    return F.array(*words)


def hamming(a: Column, b: Column) -> Column:
    """Differing bits of two word arrays."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)


def invalid(a: Column, dim: int) -> Column:
    """Why a vector cannot be indexed; null for a good one."""
    return (
        F.when(a.isNull(), "null")
        .when(F.size(a) != dim, "length")
        .when(F.exists(a, lambda x: x.isNull() | F.isnan(x)), "nan")
        .when(F.exists(a, lambda x: F.abs(x) == F.lit(float("inf"))), "infinite")
    )


def hadamard(vec: Column, signs: list[int]) -> Column:
    """Signed Walsh-Hadamard rotation for power-of-two dimensions: D^2 terms, for checks and small D."""
    dim = len(signs)
    places = F.sequence(F.lit(0), F.lit(dim - 1))
    signed = F.zip_with(vec, F.array(*[F.lit(float(s)) for s in signs]), lambda x, s: x * s)

    def output(i: Column) -> Column:
        flipped = F.zip_with(signed, places, lambda x, j: F.when(F.bit_count(i.bitwiseAND(j)) % 2 == 1, -x).otherwise(x))
        return _sum(flipped) / float(dim) ** 0.5

    return F.transform(places, output)
