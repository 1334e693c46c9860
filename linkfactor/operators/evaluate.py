"""Ranking measures over hidden links, and the baselines they are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hash_unit


def recall(ranked: DataFrame, hidden: DataFrame, ks: tuple[int, ...] = (20, 50)) -> DataFrame:
    """k, recall_truth (hits by hidden links), recall_capped (hits by min(k, hidden)) and n_sources: means over sources with a hidden link.

    ranked: row_id, col_id, rank; hidden: row_id, col_id.
    """
    truth = hidden.select("row_id", "col_id").distinct()
    sizes = truth.groupBy("row_id").agg(F.count(F.lit(1)).alias("truth"))
    hits = truth.join(ranked.where(F.col("rank") <= max(ks)).select("row_id", "col_id", "rank"), ["row_id", "col_id"])
    counted = hits.groupBy("row_id").agg(*[F.sum(F.when(F.col("rank") <= k, 1).otherwise(0)).alias(f"h{k}") for k in ks])
    each = sizes.join(counted, "row_id", "left")
    rows = each.select("truth", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.coalesce(F.col(f"h{k}"), F.lit(0)).alias("hits")) for k in ks])).alias("x"))
    return rows.groupBy(F.col("x.k").alias("k")).agg(F.avg(F.col("x.hits") / F.col("truth")).alias("recall_truth"), F.avg(F.col("x.hits") / F.least(F.col("x.k"), F.col("truth"))).alias("recall_capped"), F.count(F.lit(1)).alias("n_sources"))


def recall_by_point(ranked: DataFrame, hidden: DataFrame, ks: tuple[int, ...] = (20, 50), bits: int = 40, times: DataFrame | None = None) -> DataFrame:
    """point, k, recall_truth, n_sources, where the ids carry the point above the lower bits. times: row_id and times of sources that stand for several."""
    truth = hidden.select("row_id", "col_id").distinct()
    sizes = truth.groupBy("row_id").agg(F.count(F.lit(1)).alias("truth"))
    hits = truth.join(ranked.where(F.col("rank") <= max(ks)).select("row_id", "col_id", "rank"), ["row_id", "col_id"])
    counted = hits.groupBy("row_id").agg(*[F.sum(F.when(F.col("rank") <= k, 1).otherwise(0)).alias(f"h{k}") for k in ks])
    each = sizes.join(counted, "row_id", "left")
    each = each.withColumn("times", F.lit(1).cast("bigint")) if times is None else each.join(times, "row_id")
    rows = each.select(F.shiftright("row_id", bits).cast("int").alias("point"), "truth", "times", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.coalesce(F.col(f"h{k}"), F.lit(0)).alias("hits")) for k in ks])).alias("x"))
    share = F.sum(F.col("times") * F.col("x.hits") / F.col("truth")) / F.sum("times")
    return rows.groupBy("point", F.col("x.k").alias("k")).agg(share.alias("recall_truth"), F.sum("times").alias("n_sources"))


def ranking_measures(ranked: DataFrame, hidden: DataFrame, k: int = 20) -> DataFrame:
    """k, precision, ndcg, mrr: means over sources with a hidden link."""
    truth = hidden.select("row_id", "col_id").distinct()
    sizes = truth.groupBy("row_id").agg(F.count(F.lit(1)).alias("truth"))
    hits = truth.join(ranked.where(F.col("rank") <= k).select("row_id", "col_id", "rank"), ["row_id", "col_id"])
    gain = F.lit(1.0) / F.log2(F.col("rank") + F.lit(1.0))
    each = sizes.join(hits.groupBy("row_id").agg(F.count(F.lit(1)).alias("hits"), F.sum(gain).alias("dcg"), F.min("rank").alias("first")), "row_id", "left")
    ideal = F.aggregate(F.sequence(F.lit(1), F.least(F.col("truth"), F.lit(k)).cast("int")), F.lit(0.0), lambda s, i: s + F.lit(1.0) / F.log2(i + F.lit(1.0)))
    return each.agg(F.lit(k).alias("k"), F.avg(F.coalesce("hits", F.lit(0)) / F.lit(k)).alias("precision"), F.avg(F.coalesce("dcg", F.lit(0.0)) / ideal).alias("ndcg"), F.avg(F.coalesce(F.lit(1.0) / F.col("first"), F.lit(0.0))).alias("mrr"))


def popularity_topk(train: DataFrame, rows: DataFrame, k: int, exclude: DataFrame | None = None) -> DataFrame:
    """The most used columns for every row, without those it has already.

    Beyond the given links of a row at most k more columns are needed, so the list that is broadcast has k plus the longest given list.
    """
    longest = 0 if exclude is None else (exclude.groupBy("row_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0)
    top = train.groupBy("col_id").agg(F.count(F.lit(1)).alias("uses")).orderBy(F.desc("uses"), "col_id").limit(int(k + longest))
    best = top.agg(F.sort_array(F.collect_list(F.struct((-F.col("uses")).alias("less"), "col_id"))).alias("best")).select(F.col("best.col_id").alias("best"))
    asked, none = rows.select("row_id").distinct(), F.array().cast(f"array<{dict(top.dtypes)['col_id']}>")
    if exclude is None:
        asked = asked.withColumn("gone", none)
    else:
        gone = exclude.groupBy(F.col("row_id").alias("ex_row")).agg(F.collect_list("col_id").alias("gone"))
        asked = asked.join(gone, F.col("row_id") == F.col("ex_row"), "left").select("row_id", F.coalesce(F.col("gone").cast(f"array<{dict(top.dtypes)['col_id']}>"), none).alias("gone"))
    lists = asked.crossJoin(F.broadcast(best)).select("row_id", F.posexplode(F.slice(F.array_except("best", "gone"), 1, k)).alias("place", "col_id"))
    uses = top.select(F.col("col_id").alias("used_id"), F.col("uses").cast("double").alias("score"))
    return lists.join(F.broadcast(uses), F.col("col_id") == F.col("used_id")).select("row_id", "col_id", "score", (F.col("place") + 1).alias("rank"))


def random_topk(columns: DataFrame, rows: DataFrame, k: int, salt: str = "r") -> DataFrame:
    """k hashed-random columns for each row; for small tables, as it ranks all cells."""
    pairs = rows.select("row_id").distinct().crossJoin(columns.select("col_id").distinct())
    score = hash_unit(F.lit(salt), F.col("row_id").cast("string"), F.lit("|"), F.col("col_id").cast("string"))
    place = F.row_number().over(Window.partitionBy("row_id").orderBy(score, "col_id"))
    return pairs.withColumn("rank", place).where(F.col("rank") <= k).select("row_id", "col_id", "rank")


def same_attribute_share(ranked: DataFrame, attributes: DataFrame, k: int) -> DataFrame:
    """k, share of neighbours with the row's own attribute, and the base rate of two random entities. attributes: id, attr."""
    a, b = attributes.select(F.col("id").alias("row_id"), F.col("attr").alias("mine")), attributes.select(F.col("id").alias("col_id"), F.col("attr").alias("theirs"))
    near = ranked.where(F.col("rank") <= k).join(a, "row_id").join(b, "col_id").agg(F.avg((F.col("mine") == F.col("theirs")).cast("double")).alias("share"))
    sizes = attributes.groupBy("attr").agg(F.count(F.lit(1)).cast("double").alias("n"))
    base = sizes.agg((F.sum(F.col("n") * (F.col("n") - 1)) / (F.sum("n") * (F.sum("n") - 1))).alias("base_rate"))
    return near.crossJoin(base).select(F.lit(k).alias("k"), "share", "base_rate")


def spot_check(ranked: DataFrame, row_keys: DataFrame, col_keys: DataFrame, k: int = 5) -> DataFrame:
    """row_key, rank, col_key, score for a look at predictions. Keys: id, key."""
    a, b = row_keys.select(F.col("id").alias("row_id"), F.col("key").alias("row_key")), col_keys.select(F.col("id").alias("col_id"), F.col("key").alias("col_key"))
    return ranked.where(F.col("rank") <= k).join(a, "row_id").join(b, "col_id").select("row_key", "rank", "col_key", "score")


def overlap(approximate: DataFrame, exact: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    """k and the share of exact neighbours that an approximate search found."""
    out = None
    for k in ks:
        found = exact.where(F.col("rank") <= k).select("row_id", "col_id").join(approximate.where(F.col("rank") <= k).select("row_id", "col_id").distinct().withColumn("hit", F.lit(1)), ["row_id", "col_id"], "left")
        one = found.agg(F.lit(k).alias("k"), F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))
        out = one if out is None else out.unionByName(one)
    return out
