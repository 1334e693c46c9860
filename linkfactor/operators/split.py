"""Strong-generalization split: whole sources are held out, and a part of their links is hidden."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hash_bucket


def is_test(src: str, train: float = 0.9, salt: str = "s") -> Column:
    return hash_bucket(100, F.lit(salt), F.col(src).cast("string")) >= F.lit(round(100 * train))


def strong_split(edges: DataFrame, src: str, dst: str, train: float = 0.9, hide: float = 0.25, salt: str = "s") -> DataFrame:
    """edges with ``role``: train, given or hidden. Of a test source's links the first floor(hide * n) by hash are hidden."""
    source, target = F.col(src).cast("string"), F.col(dst).cast("string")
    test = is_test(src, train, salt)
    mine = Window.partitionBy(src)
    place = F.row_number().over(mine.orderBy(F.md5(F.concat_ws("|", F.lit(salt), source, target)), target))
    hidden = F.floor(F.lit(hide) * F.count(F.lit(1)).over(mine))
    held = edges.where(test).withColumn("role", F.when(place <= hidden, "hidden").otherwise("given"))
    return edges.where(~test).withColumn("role", F.lit("train")).unionByName(held)
