"""Exact de-duplication by Grace hashing.

Records are exchanged by the hash of their text.  Each task then splits its records by further bits of the hash into
spill files, again and again, until a bucket fits an open-addressing table that compares complete texts.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh, shared_dir, table

#: Bytes of records that a task holds before it splits them into spill files.
BUCKET_BYTES = 96 << 20
FANOUT_BITS = 4
#: Bytes of texts that the table ahead of the exchange remembers; beyond it, records pass through.
COMBINE_BYTES = 24 << 20


class ContentTable:
    """Open addressing with linear probing over 64-bit hashes; equal only if the complete contents are equal.

    Keeps for each content the least order key seen and the place of its record.
    """

    def __init__(self, size: int = 1 << 10) -> None:
        self.slots: list[int] = [-1] * size
        self.hashes: list[int] = []
        self.contents: list[bytes | None] = []
        self.best: list[tuple] = []
        self.bytes = 0

    def find(self, h: int, content: bytes | None) -> int:
        """Entry of the content, or ``-1 - slot`` of where it belongs."""
        mask = len(self.slots) - 1
        i = (h ^ (h >> 32)) & mask
        while (e := self.slots[i]) >= 0:
            if self.hashes[e] == h and self.contents[e] == content:
                return e
            i = (i + 1) & mask
        return -1 - i

    def add(self, slot: int, h: int, content: bytes | None, best: tuple) -> None:
        self.slots[slot] = len(self.hashes)
        self.hashes.append(h)
        self.contents.append(content)
        self.best.append(best)
        self.bytes += 64 + len(content or b"")
        if 2 * len(self.hashes) > len(self.slots):
            self.slots = [-1] * (4 * len(self.slots))
            mask = len(self.slots) - 1
            for e, x in enumerate(self.hashes):
                i = (x ^ (x >> 32)) & mask
                while self.slots[i] >= 0:
                    i = (i + 1) & mask
                self.slots[i] = e


def _contents(batch: pa.RecordBatch, name: str) -> list[bytes | None]:
    return batch.column(name).cast(pa.large_binary()).to_pylist()


def _orders(batch: pa.RecordBatch, ident: str, tie: str) -> list[tuple]:
    """Order keys: least id first, null ids last, then the tie hash."""
    return [(i is None, i or 0, t) for i, t in zip(batch.column(ident).to_pylist(), batch.column(tie).to_pylist(), strict=True)]


def combine(batches: Iterator[pa.RecordBatch], h: str, tie: str, limit: int = COMBINE_BYTES) -> Iterator[pa.RecordBatch]:
    """Ahead of the exchange: drop records whose equal with a smaller key has already gone out of this task."""
    seen = ContentTable()
    for batch in batches:
        keep = []
        for i, (x, content, order) in enumerate(zip(batch.column(h).to_pylist(), _contents(batch, "text"), _orders(batch, "doc_id", tie), strict=True)):
            e = seen.find(x, content)
            if e >= 0:
                if order >= seen.best[e]:
                    continue
                seen.best[e] = order
            elif seen.bytes < limit:
                seen.add(-1 - e, x, content, order)
            keep.append(i)
        yield batch if len(keep) == batch.num_rows else batch.take(pa.array(keep, pa.int64()))


class _Spill:
    """A bucket: batches in memory, and a file in the shared folder once memory was short."""

    def __init__(self, fs: pa.fs.FileSystem, path: str) -> None:
        self.fs, self.path, self.held, self.bytes, self.in_memory, self.sink, self.writer = fs, path, [], 0, 0, None, None

    def add(self, batch: pa.RecordBatch) -> None:
        size = batch.nbytes
        self.held.append(batch)
        self.bytes += size
        self.in_memory += size

    def flush(self) -> None:
        for batch in self.held:
            if self.writer is None:
                self.sink = self.fs.open_output_stream(self.path)
                self.writer = pa.ipc.new_stream(self.sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd"))
            self.writer.write_batch(batch)
        self.held, self.in_memory = [], 0

    def read(self) -> Iterator[pa.RecordBatch]:
        if self.writer is not None:
            self.writer.close()
            self.sink.close()
            with self.fs.open_input_stream(self.path) as source:
                yield from pa.ipc.open_stream(source)
            self.fs.delete_file(self.path)
        yield from self.held
        self.held = []


def grace(batches: Iterator[pa.RecordBatch], h: str, tie: str, folder: str, limit: int = BUCKET_BYTES, level: int = 0) -> Iterator[pa.RecordBatch]:
    """Survivors of one task: of equal texts, the record with the least order key."""
    fs, root = pa.fs.FileSystem.from_uri(folder)
    mine = f"{root}/{uuid.uuid4().hex}"
    if not level:
        fs.create_dir(root, recursive=True)
    fan, shift = 1 << FANOUT_BITS, 64 - FANOUT_BITS * (level + 1)
    buckets = [_Spill(fs, f"{mine}-{i}") for i in range(fan)]
    try:
        for batch in batches:
            if not batch.num_rows:
                continue
            digit = (batch.column(h).to_numpy().astype(np.int64).view(np.uint64) >> np.uint64(shift)) & np.uint64(fan - 1)
            order = np.argsort(digit, kind="stable")
            ends = np.searchsorted(digit[order], np.arange(fan + 1))
            for d in np.unique(digit):
                buckets[int(d)].add(batch.take(pa.array(order[ends[int(d)] : ends[int(d) + 1]])))
            if sum(b.in_memory for b in buckets) > limit:
                for b in buckets:
                    b.flush()
        for b in buckets:
            if b.bytes > limit and level < 14:
                yield from grace(b.read(), h, tie, folder, limit, level + 1)
            elif b.bytes:  # at the last level equal hashes remain, of which the table keeps one text each
                yield from _dedup(b.read(), h, tie)
    finally:
        for b in buckets:
            if b.sink is not None and fs.get_file_info(b.path).type == pa.fs.FileType.File:
                fs.delete_file(b.path)


def _dedup(batches: Iterator[pa.RecordBatch], h: str, tie: str) -> Iterator[pa.RecordBatch]:
    seen, rows = ContentTable(), []
    for batch in batches:
        at: dict[int, int] = {}
        for i, (x, content, order) in enumerate(zip(batch.column(h).to_pylist(), _contents(batch, "text"), _orders(batch, "doc_id", tie), strict=True)):
            e = seen.find(x, content)
            if e < 0:
                at[len(seen.hashes)] = i
                seen.add(-1 - e, x, content, order)
            elif order < seen.best[e]:
                seen.best[e] = order
                at[e] = i
        rows.append((batch.take(pa.array(list(at.values()), pa.int64())), list(at)))
    last = {e: j for j, (_, entries) in enumerate(rows) for e in entries}  # a later batch may have a better record
    for j, (batch, entries) in enumerate(rows):
        keep = [i for i, e in enumerate(entries) if last[e] == j]
        if keep:
            yield batch.take(pa.array(keep, pa.int64()))


def exact_dedup(docs: DataFrame, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """One record of each distinct ``text`` (all columns kept): that with the least ``doc_id``.

    Texts are equal if all their bytes are; null texts are equal to each other, and differ from empty ones.  Null ids
    come last.  Among records with equal text and id, the least hash of all columns wins, and of wholly equal rows one
    stays.  An empty table gives an empty table.
    """
    spark = docs.sparkSession
    h, tie = fresh(docs, "content_hash", "tie_hash")
    hashable = [c for c, t in docs.dtypes if "map<" not in t and "variant" not in t]
    keyed = docs.withColumn(h, F.xxhash64("text")).withColumn(tie, F.xxhash64(*hashable))
    folder = f"{shared_dir(spark)}/grace-{uuid.uuid4().hex}"
    few = keyed.mapInArrow(lambda it: combine(it, h, tie), keyed.schema)
    spread = few.repartition(h)
    return spread.mapInArrow(lambda it: grace(it, h, tie, folder, bucket_bytes), keyed.schema).select(*docs.columns)


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The corpus without exact copies."""
    return exact_dedup(table(spark, sf_dir, "documents"))


SQL = "SELECT doc_id, text, lang, source, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY text ORDER BY doc_id) = 1"


def stage_exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup(docs)
