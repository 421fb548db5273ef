"""Shared scratch space: written tables that every executor can read again.

Lineage is cut by writing Parquet below the folder the cluster names in
``spark.checkpoint.dir``; executors may be lost at any time, so nothing is kept
in executor memory or on executor-local disks.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_LOCAL: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share. A local one of its own only on a local master where none is set (tests); a cluster must name one."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if spark.sparkContext.getCheckpointDir():
        return spark.sparkContext.getCheckpointDir().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return _LOCAL.setdefault("dir", "file://" + tempfile.mkdtemp(prefix="netjoin-"))


_SCOPES: list[list[str]] = []


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder."""
    path = f"{shared_dir(spark)}/netjoin/{spark.sparkContext.applicationId}/{uuid.uuid4().hex[:12]}-{name}"
    for scope in _SCOPES:
        scope.append(path)
    return path


@contextmanager
def passing(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Drop everything written inside the block when it ends, but for tables handed to the function it gives."""
    written, kept = [], set()
    _SCOPES.append(written)

    def keep(table: DataFrame) -> DataFrame:
        kept.update(f.rsplit("/", 1)[0] for f in table.inputFiles())
        return table

    try:
        yield keep
    finally:
        _SCOPES.pop()
        for path in written:
            if not any(k.removeprefix("file://").endswith(path.removeprefix("file://")) for k in kept):
                drop_path(spark, path)


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a path through Hadoop's file system layer, whatever store it is in."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def materialise(df: DataFrame, name: str, *, path: str | None = None, by: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back: a durable cut of the lineage.

    With ``by``, every value of that column has a folder of its own, so that a filter on it reads nothing else.
    """
    spark = df.sparkSession
    path = path or scratch_path(spark, name)
    if by:
        df.hint("rebalance", by).write.mode("overwrite").partitionBy(by).parquet(path)
    else:
        df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def counted(df: DataFrame, name: str, *, path: str | None = None, **sums: Column) -> tuple[DataFrame, dict[str, int]]:
    """``materialise``, with the number of rows (``n``) and further aggregates taken on the way."""
    seen = Observation()
    kept = materialise(df.observe(seen, F.count(F.lit(1)).alias("n"), *(c.alias(k) for k, c in sums.items())), name, path=path)
    return kept, {k: v or 0 for k, v in seen.get.items()}


def drop_tables(*tables: DataFrame) -> None:
    """Delete written tables that nothing reads any more."""
    for t in tables:
        for folder in {f.rsplit("/", 1)[0] for f in t.inputFiles()}:
            drop_path(t.sparkSession, folder)


def release_scratch(spark: SparkSession) -> None:
    """Drop everything this application has written to its scratch space."""
    drop_path(spark, f"{shared_dir(spark)}/netjoin/{spark.sparkContext.applicationId}")
