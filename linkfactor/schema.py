"""Schemas of the tables that operators exchange."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

OBSERVATIONS = "row_id BIGINT, col_id BIGINT, y DOUBLE"
FACTORS = "id BIGINT, vec ARRAY<DOUBLE>"
SYSTEMS = "row_id BIGINT, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>, n BIGINT"
SEGMENTS = "row_id BIGINT, seg_no INT, col_ids ARRAY<BIGINT>, ys ARRAY<DOUBLE>, n_valid INT"


def require(frame: DataFrame, ddl: str) -> DataFrame:
    """The columns of ddl in its order and types; raises if one is missing."""
    wanted = T.StructType.fromDDL(ddl) if hasattr(T.StructType, "fromDDL") else T._parse_datatype_string(ddl)
    missing = [f.name for f in wanted if f.name not in frame.columns]
    if missing:
        raise ValueError(f"missing columns {missing}; found {frame.columns}")
    return frame.select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in wanted])


def reject_bad_numbers(obs: DataFrame) -> DataFrame:
    """NaN and infinite labels fail the query instead of poisoning every factor."""
    fine = F.col("y").isNotNull() & ~F.isnan("y") & (F.abs("y") < float("inf"))
    return obs.withColumn("y", F.when(fine, F.col("y")).otherwise(F.raise_error(F.lit("observation without a finite label")).cast("double")))
