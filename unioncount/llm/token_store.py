"""Token ids as compressed binary: one zstandard dictionary for all documents, one frame for each document.

The dictionary is trained on the serialised ids of the whole corpus: every chunk of some megabytes is reduced to a small
dictionary of its own, these are the samples of the next level, and so on until one training remains.  Every row keeps
the dictionary's hash and the frame's place in its shard, so that a short document is read by one seek.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, written
from .tokens import VOCABULARY, chunk_encoder, id_type, load_ranks

DICTIONARY_BYTES, LEVEL = 112 << 10, 3
#: Bytes of ids that are reduced to one dictionary at a time, its size, and what the last training takes.
CHUNK_BYTES, CHUNK_DICTIONARY, LAST_BYTES = 4 << 20, 112 << 10, 16 << 20
#: Bytes of a segment that the training picks, and of the runs that it counts.
SEGMENT, RUN = 256, 8
_INDEX = "doc_id bigint, shard int, offset bigint, n_bytes int, n_tokens int, dictionary_hash string"


def encode_ids(docs: DataFrame, ranks: dict[bytes, int]) -> DataFrame:
    """``doc_id, raw``: every text as serialised ids, written once, as training and compression both read it; a null text
    has null, an id that is no whole number is null."""
    shared = docs.sparkSession.sparkContext.broadcast(ranks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = chunk_encoder(shared.value)
        for batch in batches:
            raw = [None if t is None else encode.ids(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(raw, pa.binary())], ["doc_id", "raw"])

    texts = docs.select(F.col("doc_id").try_cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return written(texts.mapInArrow(run, "doc_id bigint, raw binary"), "ids")


def reduced(samples: list[bytes], size: int) -> bytes:
    """A dictionary of the most useful segments of ``samples``; what is too little to choose from is kept as it is."""
    import zstandard

    if sum(map(len, samples)) <= size:
        return b"".join(samples)
    try:
        return zstandard.train_dictionary(size, samples, k=SEGMENT, d=RUN, f=20, accel=2, level=LEVEL).as_bytes()
    except zstandard.ZstdError:  # fewer samples than the training accepts
        return b"".join(samples)[-size:]


def train_dictionary(ids: DataFrame, size: int = DICTIONARY_BYTES) -> bytes:
    """The shared dictionary over all of ``ids (raw)``; without any ids an empty one.

    A level reduces chunks of ``CHUNK_BYTES`` to dictionaries, which are the samples of the next; the driver trains on
    the last ``LAST_BYTES``, whatever the size of the corpus.
    """
    level = ids.where("raw is not null and length(raw) > 0").select("raw")

    def reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            for x in batch.column("raw").to_pylist():
                held.append(x)
                n += len(x)
                if n >= CHUNK_BYTES:
                    yield segments(held, n)
                    held, n = [], 0
        if held:
            yield segments(held, n)

    def segments(held: list[bytes], n: int) -> pa.RecordBatch:
        best = reduced(held, max(1024, min(CHUNK_DICTIONARY, n // 8)))
        return pa.RecordBatch.from_arrays([pa.array([best[i : i + SEGMENT] for i in range(0, len(best), SEGMENT)], pa.binary())], ["raw"])

    measure = lambda x: int(x.agg(F.coalesce(F.sum(F.length("raw")), F.lit(0))).first()[0])
    total = measure(level)
    while total > LAST_BYTES:
        level = written(level.mapInArrow(reduce, "raw binary"), "dictionaries")
        total = measure(level)
        level = level.repartition(-(-total // LAST_BYTES) or 1, "raw")
    samples = sorted(bytes(r.raw) for r in level.collect())
    if not samples:
        return b""
    return reduced(samples, min(size, max(1024, total // 8)))


def dictionary_hash(dictionary: bytes) -> str:
    return hashlib.sha256(dictionary).hexdigest()[:16]


def _codec(dictionary: bytes):
    import zstandard

    return zstandard.ZstdCompressionDict(dictionary) if dictionary else None


def encode_corpus(ids: DataFrame, dictionary: bytes, width: int = 2) -> DataFrame:
    """``doc_id, shard, offset, n_bytes, n_tokens, dictionary_hash, frame``: one row a document, in shard order.

    A shard is a partition of ``ids (doc_id, raw)``.  A null text has a null frame of 0 bytes, an empty text a frame of
    no ids; repeated rows are stored as often as they occur.  ``width`` is the bytes of an id.
    """
    shared = ids.sparkSession.sparkContext.broadcast(dictionary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        compress = zstandard.ZstdCompressor(level=LEVEL, dict_data=_codec(shared.value)).compress
        name, shard, at = dictionary_hash(shared.value), TaskContext.get().partitionId(), 0
        for batch in batches:
            raw = batch.column("raw").to_pylist()
            frames = [None if x is None else compress(x) for x in raw]
            sizes = np.array([len(x or b"") for x in frames], np.int64)
            ends = at + np.cumsum(sizes)
            n = len(raw)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(np.full(n, shard, np.int32)), pa.array(ends - sizes), pa.array(sizes.astype(np.int32)), pa.array([len(x or b"") // width for x in raw], pa.int32()), pa.array([name] * n, pa.string()), pa.array(frames, pa.binary())],
                ["doc_id", "shard", "offset", "n_bytes", "n_tokens", "dictionary_hash", "frame"],
            )
            at = int(ends[-1]) if n else at

    return ids.select("doc_id", "raw").mapInArrow(run, _INDEX + ", frame binary")


def decode(frame: bytes, dictionary: bytes, dtype: str = "<u2") -> np.ndarray:
    import zstandard

    return np.frombuffer(zstandard.ZstdDecompressor(dict_data=_codec(dictionary)).decompress(frame), dtype)


def write_store(encoded: DataFrame, dictionary: bytes, folder: str) -> None:
    """Sink: ``shard-*.bin`` files of frames end to end, ``index`` as Parquet, and the dictionary.

    A task writes under a name of its own and moves the file when it is whole, so that attempts do not mix.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = pa.fs.FileSystem.from_uri(folder)
        own = f"{root}/.part-{uuid.uuid4().hex}"
        shard = None
        with fs.open_output_stream(own) as out:
            for batch in batches:
                for x in batch.column("frame").to_pylist():
                    out.write(x or b"")
                shard = batch.column("shard")[0].as_py() if batch.num_rows else shard
                yield batch.drop_columns(["frame"])
        if shard is None:
            fs.delete_file(own)
        else:
            fs.move(own, f"{root}/shard-{shard:06d}.bin")

    fs, root = pa.fs.FileSystem.from_uri(folder)
    fs.create_dir(root, recursive=True)
    with fs.open_output_stream(f"{root}/dictionary-{dictionary_hash(dictionary)}.zdict") as out:
        out.write(dictionary)
    encoded.mapInArrow(run, _INDEX).write.mode("overwrite").parquet(f"{folder}/index")


def read_document(folder: str, row, dtype: str = "<u2") -> np.ndarray:
    """Ids of one document, given its row of the index: one seek and one frame."""
    fs, root = pa.fs.FileSystem.from_uri(folder)
    with fs.open_input_stream(f"{root}/dictionary-{row.dictionary_hash}.zdict") as source:
        dictionary = source.read()
    with fs.open_input_file(f"{root}/shard-{row.shard:06d}.bin") as source:
        return decode(source.read_at(row.n_bytes, row.offset), dictionary, dtype)


def op2_token_store(spark: SparkSession, sf_dir: str, vocabulary: str = VOCABULARY) -> DataFrame:
    """All documents as compressed ids, as ``encode_corpus`` defines them for nulls, empty and repeated rows; a row with a
    null ``doc_id`` and shard -1 holds the dictionary itself."""
    ranks = load_ranks(vocabulary)
    ids = encode_ids(table(spark, sf_dir, "documents"), ranks)
    dictionary = train_dictionary(ids)
    head = spark.createDataFrame([(None, -1, 0, len(dictionary), 0, dictionary_hash(dictionary), dictionary)], _INDEX + ", frame binary")
    return encode_corpus(ids, dictionary, int(id_type(ranks)[-1])).unionByName(head)
