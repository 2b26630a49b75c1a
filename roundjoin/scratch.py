"""Tables that cut lineage: written to the folder that driver and executors share, and removed when the session's work is done."""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL = "file:///tmp/checkpoints"
_made: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. Only a local session, whose driver and executors are one process, may lack it."""
    sc = spark.sparkContext
    at = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not at:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        at = _LOCAL
        sc.setCheckpointDir(at)
    return at.rstrip("/")


def scratch_path(spark: SparkSession, kind: str = "table") -> str:
    """A fresh path in the shared folder; clean() removes it."""
    path = f"{shared_dir(spark)}/roundjoin-{kind}-{uuid.uuid4().hex}"
    _made.append(path)
    return path


@contextmanager
def shuffles_dropped(spark: SparkSession):
    """What runs inside leaves no shuffle files: each plan's go when it has run, rather than when the driver next collects garbage, which it does once its heap
    is full and not when the disk is. A plan is one that is made inside."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


def cut(df: DataFrame) -> DataFrame:
    """Writes df as a table in the shared folder and reads it again: the lineage ends there and no executor's loss matters."""
    spark, path = df.sparkSession, scratch_path(df.sparkSession)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> bool:
    """Removes a scratch table, and says whether it was there."""
    _made.remove(path)
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return bool(at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True))


def clean(spark: SparkSession) -> int:
    """Removes what this process wrote to the shared folder, and says how many tables. Call it when no DataFrame of the library is in use any more."""
    return sum(remove(spark, path) for path in _made[::-1])
