"""Column expressions; all of them stay in generated code."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column | str, b: Column | str) -> Column:
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def bf16(x: Column) -> Column:
    """Round a double or float to 8 significant bits, ties to even, by the splitting product; finite numbers below 2**960."""
    x = x.cast("double")
    scaled = x * F.lit(float(2**45 + 1))
    return scaled - (scaled - x)


def bf16_parts(x: Column, parts: int) -> list[Column]:
    """The number as a sum of parts of 8 significant bits each, and what is left."""
    rest, out = x.cast("double"), []
    for _ in range(parts):
        out.append(bf16(rest))
        rest = rest - out[-1]
    return [*out, rest]


def hash_unit(*parts: Column) -> Column:
    """A number in [0, 2**32) from md5 of the parts, the same in other engines."""
    return F.conv(F.substring(F.md5(F.concat_ws("", *parts)), 1, 8), 16, 10).cast("bigint")


def hash_bucket(n: int, *parts: Column) -> Column:
    return F.pmod(hash_unit(*parts), F.lit(n))


def start_value(entity: Column, dim: int) -> Column:
    """Deterministic initial coordinate in [-0.5, 0.5)."""
    return F.pmod(entity * F.lit(7919) + F.lit((dim + 1) * 104729), F.lit(1000003)) / F.lit(1000003.0) - F.lit(0.5)


def packed_index(i: int, j: int, rank: int) -> int:
    """Place of (i, j), i <= j, in the packed upper triangle."""
    return i * rank - i * (i - 1) // 2 + j - i
