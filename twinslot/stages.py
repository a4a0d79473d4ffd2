"""Cutting lineage: intermediates written to the folder that all executors share, and deleted when done."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession

#: Shuffle files of a query that is over are deleted at once, not when the driver's garbage is collected.
CLEANUP_KEY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_open: ContextVar[list[DataFrame] | None] = ContextVar("twinslot_scratch", default=None)


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder. A private one is set only where none is named and all
    workers are on this machine; elsewhere they couldn't see each other's files."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        master = spark.sparkContext.master
        if not master.startswith("local"):
            raise ValueError(f"spark.checkpoint.dir isn't set: name a folder that all machines of {master} share")
        named = tempfile.mkdtemp(prefix="twinslot-")
        spark.conf.set("spark.checkpoint.dir", named)
    return named.rstrip("/")


def _own_dir(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/twinslot-{spark.sparkContext.applicationId}"


def new_path(spark: SparkSession, label: str) -> str:
    return f"{_own_dir(spark)}/{label}-{uuid.uuid4().hex}"


def cut(df: DataFrame, label: str, compression: str = "none") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends here.

    Most intermediates are a few numbers a row or compressed already, so files
    aren't compressed unless asked for.
    """
    spark = df.sparkSession
    path = new_path(spark, label)
    was = spark.conf.get(CLEANUP_KEY, "false")
    spark.conf.set(CLEANUP_KEY, "true")
    try:
        df.write.option("compression", compression).parquet(path)
    finally:
        spark.conf.set(CLEANUP_KEY, was)
    out = spark.read.schema(df.schema).parquet(path)
    out._twinslot_path = path
    if (made := _open.get()) is not None:
        made.append(out)
    return out


def _delete(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def discard(df: DataFrame) -> None:
    """Delete what ``cut`` wrote, through the file system that holds it."""
    if path := getattr(df, "_twinslot_path", None):
        _delete(df.sparkSession, path)


@contextmanager
def scratch(*kept: DataFrame) -> Iterator:
    """Tables that are cut inside are deleted at the end, except those given to the function
    that this yields: for code whose results are written before it ends."""
    made: list[DataFrame] = []
    token = _open.set(made)
    keep = {id(df) for df in kept}

    def result(df: DataFrame) -> DataFrame:
        keep.add(id(df))
        return df

    try:
        yield result
    finally:
        _open.reset(token)
        outer = _open.get()
        for df in made:
            if id(df) not in keep:
                discard(df)
            elif outer is not None:
                outer.append(df)


def clear(spark: SparkSession) -> None:
    """Delete every table that this application has written to the shared folder (results of
    queries that still read them are gone too: call it when they are written or collected)."""
    _delete(spark, _own_dir(spark))
