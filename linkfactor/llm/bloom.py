"""Bloom filters as arrays of longs, built and probed in DataFrame functions.

The filter is one row; probing puts it into the plan as a scalar subquery, so its size must
be bounded: callers pass the number of bits.
"""

from __future__ import annotations

from math import ceil, log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .cluster import settle


def places(key: Column, salt: int, hashes: int, bits: int) -> list[Column]:
    return [F.pmod(F.xxhash64(F.lit(salt), F.lit(i), key), F.lit(bits)) for i in range(hashes)]


def filter_words(keys: DataFrame, salt: int, hashes: int, bits: int) -> DataFrame:
    """keys: a column ``key``. One row with the filter in the column ``words``."""
    spots = keys.select(F.explode(F.array(*places(F.col("key"), salt, hashes, bits))).alias("spot"))
    marks = spots.select(F.shiftright("spot", 6).alias("word"), F.expr("shiftleft(1L, cast(spot % 64 as int))").alias("bits"))
    every = marks.groupBy("word").agg(F.bit_or("bits").alias("bits")).union(keys.sparkSession.range(bits // 64).select(F.col("id").alias("word"), F.lit(0).cast("bigint").alias("bits")))
    dense = every.groupBy("word").agg(F.bit_or("bits").alias("bits"))
    return dense.agg(F.transform(F.array_sort(F.collect_list(F.struct("word", "bits"))), lambda x: x["bits"]).alias("words"))


def passes(words: DataFrame, key: Column, salt: int, hashes: int, bits: int) -> Column:
    array, found = words.scalar(), None
    for spot in places(key, salt, hashes, bits):
        hit = F.get(array, F.shiftright(spot, 6).cast("int")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(spot, F.lit(64)).cast("int"))) != 0
        found = hit if found is None else found & hit
    return found


def sized(n: int, fpp: float) -> tuple[int, int]:
    """Hashes and bits for n keys."""
    hashes = max(1, round(-log(fpp, 2)))
    return hashes, 64 * max(1, ceil(n * hashes / log(2) / 64))


#: Bits of a prefilter at most (2 MB). Beyond some million keys it passes more and more rows; the join after it keeps the result exact.
PREFILTER_BITS = 1 << 24


def split(frame: DataFrame, column: Column, keys: DataFrame, salt: int = 77) -> tuple[DataFrame, DataFrame]:
    """Rows of frame whose column may be among the column ``key`` of keys, and those whose column surely isn't."""
    n = keys.count()
    hashes, bits = 2, min(PREFILTER_BITS, 64 * max(1, n * 8 // 64 + 1))
    maybe = passes(settle(filter_words(keys, salt, hashes, bits)), column, salt, hashes, bits)
    return frame.where(maybe), frame.where(~maybe)


def prefilter(frame: DataFrame, column: str, keys: DataFrame) -> DataFrame:
    """The rows that may match: fewer rows go to the shuffle of an exact join."""
    return split(frame, F.col(column), keys)[0]
