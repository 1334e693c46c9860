"""Mixing sources to target weights by Poisson replication, in DataFrame functions only.

A source with ``n`` rows, target weight ``w`` (weights are scaled to sum to one) and a
corpus of ``size`` rows (by default as many as come in) has the mean repetition rate
``size * w / n``. Each document's copy count is the inverse of that Poisson distribution
at a uniform number hashed from the seed and its doc_id, so a count depends on nothing but
the document and its source. Copies are then dealt to partitions by a second hash and
sorted by it there, which is a uniformly random global order.

Defined results: a null source is a source of its own (weight key None); a source without
a weight gets none when weights are given; null doc_ids share one hash key; repeated rows
get the same count each; an empty table gives an empty table. Extra columns are carried,
and helper columns never meet them, as they are nested in one struct of a free name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .cluster import settle

SEED = "mix-1"
#: Per-source tables of up to so many rows are broadcast; beyond it the join is left to Spark.
BROADCAST_SOURCES = 20_000
_DIGITS = 13


def unit_hash(*parts: Column) -> Column:
    """A number in [0, 1) with 52 hashed bits, the same in any SQL engine with md5."""
    return unit_int(*parts) / F.lit(float(16**_DIGITS))


def unit_int(*parts: Column) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, _DIGITS), 16, 10).cast("bigint")


def poisson_table(rate: Column) -> Column:
    """Cumulative probabilities of 0, 1, 2, ... copies, until the rest is below double precision."""
    last = (F.ceil(rate + 10 * F.sqrt(rate)) + 20).cast("int")
    start = F.struct((-rate).alias("logp"), F.array(F.exp(-rate)).alias("cdf"))

    def step(so_far: Column, k: Column) -> Column:
        logp = so_far["logp"] + F.log(rate) - F.log(k.cast("double"))
        return F.struct(logp.alias("logp"), F.concat(so_far["cdf"], F.array(F.element_at(so_far["cdf"], -1) + F.exp(logp))).alias("cdf"))

    whole = F.aggregate(F.sequence(F.lit(1), last), start, step)["cdf"]
    return F.when(rate > 0, whole).otherwise(F.array(F.lit(1.0)))


def source_rates(docs: DataFrame, weights: dict | None = None, size: int | None = None, source: str = "source") -> DataFrame:
    """One row per source: its rows, mean repetition rate and Poisson table."""
    counts = docs.groupBy(F.col(source).alias("of_source")).agg(F.count(F.lit(1)).alias("n_rows"))
    counts = settle(counts)
    if weights is None:
        weighted = counts.withColumn("weight", F.lit(1.0))
    else:
        pairs = F.create_map(*[F.lit(x) for k, v in weights.items() if k is not None for x in (k, float(v))]) if any(k is not None for k in weights) else None
        known = F.try_element_at(pairs, F.col("of_source")) if pairs is not None else F.lit(None).cast("double")
        weighted = counts.withColumn("weight", F.coalesce(F.when(F.col("of_source").isNull(), F.lit(float(weights.get(None, 0.0)))), known, F.lit(0.0)))
    total, rows = weighted.agg(F.sum("weight"), F.sum("n_rows")).first()
    if not total:
        return weighted.withColumns({"rate": F.lit(0.0), "cdf": F.array(F.lit(1.0))})
    goal = float(rows if size is None else size)
    rated = weighted.withColumn("rate", F.lit(goal) * F.col("weight") / F.lit(float(total)) / F.col("n_rows"))
    return rated.withColumn("cdf", poisson_table(F.col("rate")))


def mix_sources(docs: DataFrame, weights: dict | None = None, size: int | None = None, seed: str = SEED, source: str = "source", key: str = "doc_id") -> DataFrame:
    """Replicate documents by their Poisson counts and shuffle globally.

    Returns the columns of docs, then ``copy`` (1, 2, ... of a document) and
    ``shuffle_key`` (long); these replace columns of the same names.
    """
    rates = settle(source_rates(docs, weights, size, source).select("of_source", "cdf"))
    rates = F.broadcast(rates) if rates.count() <= BROADCAST_SOURCES else rates
    names = [c for c in docs.columns if c not in ("copy", "shuffle_key")]
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"))
    drawn = packed.join(rates, packed["row"][source].eqNullSafe(rates["of_source"]))
    who = F.coalesce(F.col("row")[key].cast("string"), F.lit("null"))
    drawn = drawn.select("row", _copies(unit_hash(F.lit(seed), who)).alias("copies"))
    copies = drawn.filter("copies > 0").select("row", F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("copy"))
    keyed = copies.select("row", "copy", unit_int(F.lit(seed), F.lit("place"), who, F.col("copy").cast("string")).alias("shuffle_key"))
    dealt = keyed.repartition(F.col("shuffle_key")).sortWithinPartitions("shuffle_key")
    return dealt.select(*[F.col("row")[c].alias(c) for c in names], "copy", "shuffle_key")


def _copies(draw: Column) -> Column:
    return F.aggregate("cdf", F.lit(0), lambda n, c: n + F.when(c <= draw, 1).otherwise(0))
