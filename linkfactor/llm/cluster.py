"""What the operators need from the session: the shared folder, lineage cuts and row sources."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where the setting is missing a temporary folder is used, on one machine only (tests).
    """
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if not configured:
        context = spark.sparkContext
        configured = context.getCheckpointDir()
        if not configured:
            if not context.master.startswith("local") or context.master.startswith("local-cluster"):
                raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
            configured = "file://" + tempfile.mkdtemp(prefix="linkfactor-")
            context.setCheckpointDir(configured)
    return configured


def scratch(spark: SparkSession, label: str) -> str:
    return f"{shared_folder(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"


def settle(frame: DataFrame) -> DataFrame:
    """Materialize a small frame in the shared folder and cut its lineage."""
    shared_folder(frame.sparkSession)
    return frame.checkpoint()


def settle_table(frame: DataFrame, label: str, hashes: tuple[str, ...] = ()) -> DataFrame:
    """Like settle, as compressed Parquet for frames that grow with the text; columns of hashes get no dictionary."""
    spark = frame.sparkSession
    path = scratch(spark, label)
    frame.write.options(**{f"parquet.enable.dictionary#{c}": "false" for c in hashes}).parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


def drop(spark: SparkSession, path: str) -> None:
    """Delete a folder through Hadoop's file system, whatever store it is in."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
