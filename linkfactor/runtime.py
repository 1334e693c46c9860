"""Session services: shipping the package, the shared folder, generations of tables."""

from __future__ import annotations

import os
import tempfile
import threading
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Make the package importable in Python workers, where the environment doesn't already."""
    home = Path(__file__).resolve().parent.parent
    context = spark.sparkContext
    known = [os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    if str(home) not in known and context.applicationId not in _SHIPPED:
        _SHIPPED.add(context.applicationId)
        target = Path(tempfile.mkdtemp(prefix="linkfactor-ship-")) / "linkfactor_package.zip"
        with zipfile.ZipFile(target, "w") as z:
            for p in sorted((home / "linkfactor").rglob("*.py")):
                z.write(p, p.relative_to(home))
        context.addPyFile(str(target))
    return spark


def on_one_machine(spark: SparkSession) -> bool:
    """Whether driver and executors are one process, so that a local folder is shared."""
    return spark.sparkContext.master.startswith("local") and not spark.sparkContext.master.startswith("local-cluster")


def executors(spark: SparkSession) -> int:
    """Executors that are there now (1 where the driver does the work)."""
    return max(1, len(spark.sparkContext._jsc.sc().statusTracker().getExecutorInfos()) - (0 if on_one_machine(spark) else 1))


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; on one machine a temporary folder where that is unset."""
    configured = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not configured:
        if not on_one_machine(spark):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        configured = "file://" + tempfile.mkdtemp(prefix="linkfactor-")
        spark.sparkContext.setCheckpointDir(configured)
    return configured


_MADE: ContextVar[list[str] | None] = ContextVar("made", default=None)


def scratch(spark: SparkSession, label: str) -> str:
    path = f"{shared_folder(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    if (made := _MADE.get()) is not None:
        made.append(path)
    return path


@contextmanager
def passing_tables(spark: SparkSession) -> Iterator[None]:
    """Tables that this thread writes to the shared folder meanwhile are deleted at the end."""
    made: list[str] = []
    token = _MADE.set(made)
    try:
        yield
    finally:
        _MADE.reset(token)
        for path in made:
            drop_path(spark, path)


_CLEANUP, _GATE, _WRITERS = "spark.sql.classic.shuffleDependency.fileCleanup.enabled", threading.Lock(), {}


@contextmanager
def passing_shuffles(spark: SparkSession) -> Iterator[None]:
    """What is written meanwhile leaves no shuffle files behind; the setting is put back when the last writer is done."""
    with _GATE:
        n, before = _WRITERS.get(spark) or (0, spark.conf.get(_CLEANUP, None))
        _WRITERS[spark] = (n + 1, before)
        spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        with _GATE:
            n, before = _WRITERS.pop(spark)
            if n > 1:
                _WRITERS[spark] = (n - 1, before)
            elif before is None:
                spark.conf.unset(_CLEANUP)
            else:
                spark.conf.set(_CLEANUP, before)


def write_passing(frame: DataFrame, path: str) -> None:
    """Write a frame whose shuffles nobody reads again."""
    with passing_shuffles(frame.sparkSession):
        frame.write.parquet(path)


def generation(frame: DataFrame, label: str) -> DataFrame:
    """Write a frame to the shared folder and read it back: lineage is cut and survives lost executors, and the shuffles behind it go."""
    return generation_at(frame, label)[0]


def generation_at(frame: DataFrame, label: str) -> tuple[DataFrame, str]:
    """The same, with the folder."""
    spark, path = frame.sparkSession, scratch(frame.sparkSession, label)
    write_passing(frame, path)
    return spark.read.schema(frame.schema).parquet(path), path


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a table of the shared folder through Hadoop's file system, whatever store it is in."""
    jvm = spark._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
