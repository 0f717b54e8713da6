"""Token counts of documents: pieces are counted once for each distinct pre-token and joined to the frequencies.

Neither ids nor pieces are ever made for a document.  The most frequent pre-tokens (a table of fixed size) are looked
up where the documents are; all others go through a join by pre-token.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, worker_cache, written
from .tokens import SPLIT, VOCABULARY, encoder, load_ranks

#: Entries of the broadcast table of frequent pre-tokens; the join handles all the rest.
FREQUENT = 1 << 18


def _splitter():
    cache = worker_cache("split")
    if "find" not in cache:
        import regex

        cache["find"] = regex.compile(SPLIT).findall
    return cache["find"]


def vocabulary_counts(docs: DataFrame, ranks: dict[bytes, int]) -> DataFrame:
    """``piece, total, n``: every distinct pre-token, its occurrences in the corpus, and the pieces it splits into."""
    shared = docs.sparkSession.sparkContext.broadcast(ranks)

    def occurrences(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find, seen = _splitter(), Counter()
        for batch in batches:
            for t in batch.column("text").to_pylist():
                seen.update(find(t or ""))
                if len(seen) > 1_000_000:  # memory of a task; the aggregate adds the parts up
                    yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], ["piece", "k"])
                    seen.clear()
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], ["piece", "k"])

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(shared.value).encode_ordinary
        for batch in batches:
            n = pa.array([len(encode(x)) for x in batch.column("piece").to_pylist()], pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column("piece"), batch.column("total"), n], ["piece", "total", "n"])

    totals = docs.select("text").mapInArrow(occurrences, "piece string, k bigint").groupBy("piece").agg(F.sum("k").alias("total"))
    return totals.mapInArrow(pieces, "piece string, total bigint, n int")


def frequency_cut(counted: DataFrame, frequent: int) -> int:
    """Least number of occurrences that at most ``frequent`` pre-tokens reach, from a histogram of eighths of octaves."""
    eighth = F.floor(F.log2("total") * 8)
    bins = counted.groupBy(eighth.alias("b")).agg(F.count("*").alias("n"), F.min("total").alias("least")).collect()
    cut, room = 1 << 62, frequent
    for r in sorted(bins, key=lambda r: -r.b):
        room -= r.n
        if room < 0:
            break
        cut = r.least
    return cut


def token_counts(docs: DataFrame, ranks: dict[bytes, int], frequent: int = FREQUENT) -> DataFrame:
    """``doc_id, n_tokens`` for every row of ``docs``, repeated rows and ids included; null and empty texts have 0."""
    spark = docs.sparkSession
    counted = written(vocabulary_counts(docs, ranks), "vocabulary")
    hot = {r.piece: r.n for r in counted.where(F.col("total") >= frequency_cut(counted, frequent)).select("piece", "n").collect()}
    shared = spark.sparkContext.broadcast(hot)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find, known = _splitter(), shared.value
        for batch in batches:
            ids, keys = batch.column("doc_id").to_pylist(), batch.column("h").to_pylist()
            rows: tuple[list, ...] = ([], [], [], [], [], [])
            for i, h, t in zip(ids, keys, batch.column("text").to_pylist(), strict=True):
                here, rest = 0, []
                for piece, k in Counter(find(t or "")).items():
                    n = known.get(piece)
                    if n is None:
                        rest.append((piece, k))
                    else:
                        here += n * k
                # the first row of a document carries what was looked up here
                for piece, k, n, one in [(*rest[0], here, 1), *((p, k, 0, 0) for p, k in rest[1:])] if rest else [(f"\0{h}", 0, here, 1)]:
                    for column, x in zip(rows, (i, h, piece, k, n, one), strict=True):
                        column.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, (pa.int64(), pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int32()), strict=True)], ["doc_id", "h", "piece", "k", "here", "one"])

    keyed = docs.select(F.col("doc_id").try_cast("bigint").alias("doc_id"), F.xxhash64("text").alias("h"), "text")
    parts = keyed.mapInArrow(split, "doc_id bigint, h bigint, piece string, k int, here bigint, one int")
    # a document without rare pre-tokens sends one row whose key is its own and matches nothing
    joined = parts.join(counted.select("piece", "n"), "piece", "left").select("doc_id", "h", (F.col("here") + F.col("k") * F.coalesce("n", F.lit(0))).alias("here"), "one")
    sums = joined.groupBy("doc_id", "h").agg(F.sum("here").alias("n"), F.sum("one").cast("int").alias("rows"))
    # equal rows were added up together: share the sum among them
    return sums.select("doc_id", (F.col("n") / F.col("rows")).cast("bigint").alias("n_tokens"), F.explode(F.sequence(F.lit(1), F.col("rows"))).alias("row")).select("doc_id", "n_tokens")


def op8_token_counts(spark: SparkSession, sf_dir: str, vocabulary: str = VOCABULARY) -> DataFrame:
    """``doc_id, n_tokens`` of every document under a public byte-level vocabulary: repeated rows and ids as often as they
    occur, null and empty texts with 0, ids that are no whole numbers as null; an empty table gives no rows."""
    return token_counts(table(spark, sf_dir, "documents"), load_ranks(vocabulary))
