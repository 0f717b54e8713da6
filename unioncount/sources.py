"""Inputs: the given tables, holder/element relations made from them, generated sets, packed sketches."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def elements(df: DataFrame, holder, element) -> DataFrame:
    """``holder, element`` as text; null elements are members of no set."""
    as_column = lambda x: F.col(x) if isinstance(x, str) else x
    return df.select(as_column(holder).cast("string").alias("holder"), as_column(element).cast("string").alias("element")).where("element is not null")


def _events_hour(spark: SparkSession, d: str) -> DataFrame:
    return elements(load(spark, d, "events"), F.hour("ts"), "user_id")


#: Holder/element relations by name: the DataFrame and the same rows in SQL.
FIXTURES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "docs_text": (lambda s, d: elements(load(s, d, "documents"), "source", "text"), "SELECT source AS holder, text AS element FROM documents"),
    "docs_word": (lambda s, d: elements(load(s, d, "documents").select("source", F.explode(F.split(F.lower("text"), " ")).alias("e")), "source", "e"), "SELECT source AS holder, unnest(string_split(lower(text), ' ')) AS element FROM documents"),
    "docs_line": (lambda s, d: elements(load(s, d, "documents").select("source", F.explode(F.split("text", "\n")).alias("e")), "source", "e"), "SELECT source AS holder, unnest(string_split(text, chr(10))) AS element FROM documents"),
    "goods": (lambda s, d: elements(load(s, d, "lineitem"), F.col("l_suppkey") % 20, "l_orderkey"), "SELECT (l_suppkey % 20)::VARCHAR AS holder, l_orderkey::VARCHAR AS element FROM lineitem"),
    "goods_by_nation": (
        lambda s, d: elements(load(s, d, "lineitem").join(load(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")), "s_nationkey", "l_orderkey"),
        "SELECT s_nationkey::VARCHAR AS holder, l_orderkey::VARCHAR AS element FROM lineitem JOIN supplier ON l_suppkey = s_suppkey",
    ),
    "patients": (lambda s, d: elements(load(s, d, "orders"), "o_orderpriority", "o_custkey"), "SELECT o_orderpriority AS holder, o_custkey::VARCHAR AS element FROM orders"),
    "reach": (lambda s, d: elements(load(s, d, "events"), "event_type", "user_id"), "SELECT event_type AS holder, user_id::VARCHAR AS element FROM events"),
    "clients": (_events_hour, "SELECT hour(ts)::VARCHAR AS holder, user_id::VARCHAR AS element FROM events"),
    "hosts": (
        lambda s, d: elements(load(s, d, "pages"), F.regexp_extract("url", r"^https?://[^/]+/([^/?#]*)", 1), F.try_parse_url("url", F.lit("HOST"))),
        r"SELECT regexp_extract(url, '^https?://[^/]+/([^/?#]*)', 1) AS holder, regexp_extract(url, '^https?://([^/:?#]+)', 1) AS element FROM pages",
    ),
    "parts_by_nation": (
        lambda s, d: elements(load(s, d, "lineitem").join(load(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(load(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")), "c_nationkey", "l_partkey"),
        "SELECT c_nationkey::VARCHAR AS holder, l_partkey::VARCHAR AS element FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey",
    ),
    "conv_word": (lambda s, d: elements(load(s, d, "conversations").select("role", F.explode(F.split(F.lower("text"), " ")).alias("e")), "role", "e"), "SELECT role AS holder, unnest(string_split(lower(text), ' ')) AS element FROM conversations"),
}


def fixture(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return FIXTURES[name][0](spark, sf_dir)


def fixture_sql(name: str) -> str:
    return FIXTURES[name][1]


def gen_sets(spark: SparkSession, n: int, d: int, overlap: bool = False) -> DataFrame:
    """``n`` elements over ``d`` holders; with ``overlap`` the next holder has each element too."""
    ids = spark.range(n)
    first = elements(ids, F.col("id") % d, "id")
    return first.union(elements(ids, (F.col("id") + 1) % d, "id")) if overlap else first


class PackedSketchSource(DataSource):
    """Reads packed sketches (one file per holder, 8-byte little-endian arrays) from a folder: ``holder, arr, bits``."""

    @classmethod
    def name(cls) -> str:
        return "packed_sketch"

    def schema(self) -> str:
        return "holder string, arr int, bits bigint"

    def reader(self, schema) -> DataSourceReader:
        return _PackedReader(self.options["path"])


class _PackedReader(DataSourceReader):
    """Lists and reads through the file system that the path names, so that the folder may be a shared one."""

    def __init__(self, path: str) -> None:
        self.path = path

    def partitions(self):
        from pyarrow import fs

        files, root = fs.FileSystem.from_uri(self.path)
        found = files.get_file_info(fs.FileSelector(root))
        return [InputPartition(f.base_name) for f in sorted(found, key=lambda f: f.base_name) if f.extension == "sketch"]

    def read(self, partition):
        import struct

        from pyarrow import fs

        files, root = fs.FileSystem.from_uri(self.path)
        with files.open_input_stream(f"{root}/{partition.value}") as source:
            data = source.read()
        for arr, (bits,) in enumerate(struct.iter_unpack("<q", data)):
            if bits:
                yield partition.value[: -len(".sketch")], arr, bits


def write_packed(batches, path: str):
    """Writes packed sketches (``holder, packed``) as files under ``path``; a file appears when it is whole."""
    import uuid

    import pandas as pd
    from pyarrow import fs

    files, root = fs.FileSystem.from_uri(path)
    files.create_dir(root, recursive=True)
    for pdf in batches:
        for holder, data in zip(pdf["holder"], pdf["packed"]):
            part = f"{root}/.{uuid.uuid4().hex}"
            with files.open_output_stream(part) as out:
                out.write(b"".join(data[i : i + 8][::-1] for i in range(0, len(data), 8)))
            files.move(part, f"{root}/{holder}.sketch")
        yield pd.DataFrame({"n": [len(pdf)]})
