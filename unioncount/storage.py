"""Folders for written tables: in the shared folder of the session."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

_WRITTEN: list[str] = []


def folder(spark: SparkSession, tag: str) -> str:
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base and sc._jsc.sc().getCheckpointDir().isDefined():
        base = sc._jsc.sc().getCheckpointDir().get()
    if not base:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="unioncount-")
        sc.setCheckpointDir(base)
    path = f"{base.rstrip('/')}/{tag}-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    return path


def written(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written as Parquet in the shared folder and read again: its lineage ends, and it is computed once."""
    path = folder(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


_ONCE: dict[tuple, DataFrame] = {}


def written_once(spark: SparkSession, key: tuple, make: Callable[[], DataFrame], tag: str) -> DataFrame:
    """What ``make`` gives, written the first time that this session asks for ``key``."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _ONCE:
        _ONCE[key] = written(make(), tag)
    return _ONCE[key]


def clear_written(spark: SparkSession) -> None:
    """Delete what this process has written, once no DataFrame that reads it is needed any more."""
    _ONCE.clear()
    while _WRITTEN:
        path = spark._jvm.org.apache.hadoop.fs.Path(_WRITTEN.pop())
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
