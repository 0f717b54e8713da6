"""Helpers shared by the corpus operators: shared-folder tables, fresh column names, worker caches."""

from __future__ import annotations

import sys
import tempfile
import types
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """Folder that every executor reaches: ``spark.checkpoint.dir``; a temporary one only in local mode."""
    sc = spark.sparkContext
    found = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not found and sc._jsc.sc().getCheckpointDir().isDefined():
        found = sc._jsc.sc().getCheckpointDir().get()
    if not found:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="unioncount-")
        sc.setCheckpointDir(found)
    return found.rstrip("/")


def scratch(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"


_WRITTEN: list[str] = []


def clear_written(spark: SparkSession) -> None:
    """Delete the tables that this process has written, once no DataFrame that reads them is needed any more."""
    while _WRITTEN:
        path = spark._jvm.org.apache.hadoop.fs.Path(_WRITTEN.pop())
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def written(df: DataFrame, tag: str) -> DataFrame:
    """Cut lineage: write ``df`` as Parquet in the shared folder and read it again.

    A lost executor then costs a re-read and never a recomputation with other random or arrival order.
    """
    spark = df.sparkSession
    path = scratch(spark, tag)
    df.write.parquet(path)
    _WRITTEN.append(path)
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fresh(df: DataFrame, *bases: str) -> list[str]:
    """Column names that do not clash (case-insensitively) with those of ``df``."""
    taken = {c.lower() for c in df.columns}
    names = []
    for base in bases:
        name = base
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        names.append(name)
    return names


def least_by_hash(df: DataFrame, key: Column, k: int, *ties: str) -> list:
    """The ``k`` rows of the least ``key`` (a 64-bit hash), in its order.  A threshold that follows from the number of
    rows comes first, so that all tasks together send a little over ``k`` rows to the driver."""
    n = df.count()
    share = min(1.0, (1.2 * k + 6 * k**0.5 + 10) / max(1, n))
    name = fresh(df, "hash_key")[0]
    while True:
        keyed = df.withColumn(name, key)
        some = keyed if share >= 1 else keyed.where(F.col(name) < int(-(2**63) + share * 2**64))
        rows = some.orderBy(name, *ties).limit(k).drop(name).collect()
        if share >= 1 or len(rows) == k:
            return rows
        share *= 2


def word_hashes(text: Column) -> Column:
    """``array<bigint>`` of 64-bit hashes of the lower-cased, whitespace-separated words; null text gives null."""
    words = F.filter(F.split(F.lower(text), r"\s+"), lambda w: w != "")
    return F.transform(words, lambda w: F.xxhash64(w))


def worker_cache(name: str) -> dict:
    """A dict that outlives a task: kept in the worker process, since functions are pickled by value."""
    key = f"_unioncount_cache_{name}"
    if key not in sys.modules:
        sys.modules[key] = types.ModuleType(key)
        sys.modules[key].cache = {}
    return sys.modules[key].cache


def whole_groups(batches: Iterator[pa.RecordBatch], key: str, rows: int = 200_000) -> Iterator[pa.Table]:
    """Regroup a partition that is sorted by ``key`` into tables that never cut a group in two."""
    import numpy as np

    held: list[pa.RecordBatch] = []
    n = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        n += batch.num_rows
        if n < rows:
            continue
        whole = pa.Table.from_batches(held)
        keys = whole.column(key).to_numpy()
        last = int(np.flatnonzero(keys != keys[-1])[-1]) + 1 if (keys != keys[-1]).any() else 0
        if last:
            yield whole.slice(0, last)
        held = whole.slice(last).combine_chunks().to_batches()
        n = whole.num_rows - last
        rows = max(rows, 2 * n)
    if held:
        yield pa.Table.from_batches(held)


def ragged(column: pa.Array | pa.ChunkedArray):
    """``(values, offsets)`` of a list column; null lists are empty."""
    import numpy as np

    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
    lengths = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    offsets = np.zeros(len(column) + 1, np.int64)
    np.cumsum(lengths, out=offsets[1:])
    return column.flatten().to_numpy(zero_copy_only=False), offsets
