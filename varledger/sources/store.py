"""Intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType


def shared_dir(spark: SparkSession) -> str:
    """Folder that the cluster names in ``spark.checkpoint.dir``; only where that
    is unset (one process, as in tests) a temporary one, kept for the session."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.varledger.store.dir", None)
    if named is None:
        named = "file://" + tempfile.mkdtemp(prefix="varledger-store-")
        spark.conf.set("spark.varledger.store.dir", named)
    return named.rstrip("/")


def _write(df: DataFrame, name: str) -> str:
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return path


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df``, written once and read back: several consumers of one query share
    it, and a lost executor costs no more than the part it was reading."""
    return df.sparkSession.read.schema(df.schema).parquet(_write(df, name))


_SAVED: dict[tuple, tuple[str, StructType]] = {}


def _version(spark: SparkSession, path: str) -> tuple:
    """(file, length, modification time) of all files under a path."""
    jvm = spark.sparkContext._jvm
    root = jvm.org.apache.hadoop.fs.Path(path)
    fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    files, out = fs.listFiles(root, True), []
    while files.hasNext():
        f = files.next()
        out.append((f.getPath().toString(), f.getLen(), f.getModificationTime()))
    return tuple(sorted(out))


def _key(spark: SparkSession, name: str, inputs: list[str]) -> tuple:
    return (spark.sparkContext.applicationId, name, *[_version(spark, p) for p in inputs])


def saved(spark: SparkSession, name: str, inputs: list[str], build: Callable[[], DataFrame]) -> DataFrame:
    """What ``build`` makes, written once an application for this version of the
    input files: profiles and ledgers are made once and asked many times, and
    made again when a file changes."""
    key = _key(spark, name, inputs)
    if key not in _SAVED:
        rows = build()
        _SAVED[key] = (_write(rows, name), rows.schema)
    return made(spark, name, inputs)


def made(spark: SparkSession, name: str, inputs: list[str]) -> DataFrame | None:
    """What :func:`saved` has written already, or None."""
    held = _SAVED.get(_key(spark, name, inputs))
    return held and spark.read.schema(held[1]).parquet(held[0])
