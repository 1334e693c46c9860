"""Functions for SQL users: Arrow scalar and aggregate functions and table functions."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def gram_of(vectors: pd.Series) -> list:
    """Packed Gram triangle of a group of vectors."""
    x = np.array(vectors.tolist(), dtype=float)
    i, j = np.triu_indices(x.shape[1])
    return (x.T @ x)[i, j].tolist()


@F.pandas_udf(T.BinaryType())
def bf16_bytes(vectors: pd.Series) -> pd.Series:
    """Two bytes a coordinate."""
    from ..operators.solvers import bf16_pack

    return vectors.map(lambda v: bf16_pack(np.array(v, dtype=np.float32)).tobytes())


@F.udtf(returnType="link string, place int")
class LinksOf:
    """The hrefs of a page in order."""

    def eval(self, html: str) -> Iterator[tuple[str, int]]:
        for n, m in enumerate(re.finditer(r'href="([^"]*)"', html or "")):
            yield m[1], n


@F.udtf(returnType="seg_no int, col_ids array<bigint>, n_valid int")
class SegmentsOf:
    """A row's columns in segments of one width, padded with -1."""

    def eval(self, col_ids: list, width: int) -> Iterator[tuple[int, list, int]]:
        for n, at in enumerate(range(0, len(col_ids or []), width)):
            part = list(col_ids[at : at + width])
            yield n, part + [-1] * (width - len(part)), len(part)


def register(spark: SparkSession) -> None:
    spark.udf.register("gram_of", gram_of)
    spark.udf.register("bf16_bytes", bf16_bytes)
    spark.udtf.register("links_of", LinksOf)
    spark.udtf.register("segments_of", SegmentsOf)
