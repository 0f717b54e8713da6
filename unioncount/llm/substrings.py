"""Repeated passages across documents: winnowed anchors as seeds, extension both ways, maximal spans.

Texts are sequences of whitespace-separated words.  Any passage of ``THRESHOLD`` words (a window) has one anchor: the
least hash among its runs of ``SEED_WORDS`` words.  Documents are joined on anchors.  An occurrence of a shared anchor
is extended to the left and to the right over all windows that chose it, against all other occurrences at once:
windows are compared by hashes of their whole content, which holds for every pair of occurrences without forming the
pairs.  Runs of windows with the same occurrences are one passage, and each of its occurrences is a row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import ragged, table, whole_groups, written
from .simhash import _mix

#: Least length of a reported passage, and length of a seed, in words.
THRESHOLD, SEED_WORDS = 50, 20
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.empty(n + 1, np.uint64)
    out[0] = 1
    out[1:] = np.uint64(base)
    return np.multiply.accumulate(out)


def run_hashes(words: np.ndarray, length: int) -> np.ndarray:
    """Hashes of all runs of ``length`` words, by prefix sums of a polynomial modulo 2^64."""
    n = len(words)
    if n < length:
        return np.empty(0, np.uint64)
    prefix = np.zeros(n + 1, np.uint64)
    np.cumsum(words.view(np.uint64) * _powers(_INVERSE, n)[:n], out=prefix[1:])
    return _mix((prefix[length:] - prefix[:-length]) * _powers(_BASE, n)[: n - length + 1], 5)


def anchors_of_windows(words: np.ndarray, threshold: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the seeds, and for each window the place of its anchor (the first of the least hashes)."""
    seeds = run_hashes(words, seed)
    width = threshold - seed + 1
    if len(seeds) < width:
        return seeds, np.empty(0, np.int64)
    best = np.lib.stride_tricks.sliding_window_view(seeds, width).argmin(axis=1)
    return seeds, best + np.arange(len(best))


def _words(docs: DataFrame, *columns: str) -> DataFrame:
    words = F.transform(F.filter(F.split("text", r"\s+"), lambda w: w != ""), lambda w: F.xxhash64(w))
    return docs.select(*columns, words.alias("words"))


def shared_passages(docs: DataFrame, threshold: int = THRESHOLD, seed: int = SEED_WORDS) -> DataFrame:
    """``doc_id, start_word, n_words, passage, n_docs, row``: every occurrence of every passage that documents share.

    A passage is a maximal run of windows of ``threshold`` words with the same occurrences: within it no occurrence
    begins or ends.  The rows of one ``passage`` are all its occurrences, in ``n_docs`` documents, so the partners of a
    row are the rows of its passage and no pair is formed or left out; ``passage_pairs`` puts the passages of two
    documents together to their maximal common spans.  Every shared window of a document is in one passage.

    Documents are told apart by id and text together (``row``): repeated rows are one document, equal texts under two
    ids repeat each other.  Repeats within one document alone are not reported.  Rows with a null id (or one that is no whole
    number) and texts below the threshold have no passages.  Windows count as equal if their anchor and their whole
    content have equal 64-bit hashes, which together are as good as 128 bits.
    """
    keyed = docs.where(F.col("doc_id").try_cast("bigint").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").try_cast("bigint").alias("doc_id"), F.xxhash64("doc_id", "text").alias("row"), "text")

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values, off = ragged(batch.column("words"))
            rows = batch.column("row").to_numpy()
            found: list[tuple] = []
            for i in range(batch.num_rows):
                seeds, at = anchors_of_windows(values[off[i] : off[i + 1]], threshold, seed)
                if len(at):
                    at = np.unique(at)
                    found.append((seeds[at].view(np.int64), np.full(len(at), rows[i]), at.astype(np.int32)))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*found)], ["anchor", "row", "at"])

    anchors = written(_words(keyed, "row").mapInArrow(find, "anchor bigint, row bigint, at int"), "anchors")
    shared = anchors.groupBy("anchor").agg(F.min("row").alias("a"), F.max("row").alias("b")).where("a <> b").select("anchor")
    places = anchors.join(shared, "anchor").groupBy("row").agg(F.collect_set("at").alias("places"))
    texts = keyed.join(places, "row")

    def extend(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Windows around the shared anchors: those that chose the anchor, from the leftmost to the rightmost."""
        for batch in batches:
            values, off = ragged(batch.column("words"))
            wanted, woff = ragged(batch.column("places"))
            rows, ids = batch.column("row").to_pylist(), batch.column("doc_id").to_pylist()
            out: tuple[list, ...] = ([], [], [], [], [])
            for i in range(batch.num_rows):
                words = values[off[i] : off[i + 1]]
                seeds, at = anchors_of_windows(words, threshold, seed)
                windows = run_hashes(words, threshold).view(np.int64)
                for place in np.sort(wanted[woff[i] : woff[i + 1]]):
                    lo, hi = np.searchsorted(at, place), np.searchsorted(at, place, side="right")
                    if lo < hi:
                        for column, x in zip(out, (int(seeds[place].view(np.int64)), rows[i], ids[i], int(lo), windows[lo:hi].tobytes()), strict=True):
                            column.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary()), strict=True)], ["anchor", "row", "doc_id", "first", "windows"])

    extended = _words(texts, "row", "doc_id", "places").mapInArrow(extend, "anchor bigint, row bigint, doc_id bigint, first int, windows binary")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Occurrences of each anchor against each other; runs of windows with the same occurrences.

        Occurrences of a window are told by the least of them and by a sum of hashes of all, as seen from the least.
        """
        for group in whole_groups(batches, "anchor", 50_000):
            parts = [np.frombuffer(x, np.int64) for x in group.column("windows").to_pylist()]
            sizes = np.array([len(x) for x in parts])
            window = np.concatenate(parts)
            owner = np.repeat(np.arange(len(parts)), sizes)
            start = np.arange(len(window)) - np.repeat(np.cumsum(sizes) - sizes, sizes) + group.column("first").to_numpy()[owner]
            row, doc = group.column("row").to_numpy()[owner], group.column("doc_id").to_numpy()[owner]
            order = np.lexsort((start, row, window))
            w, r, s = window[order], row[order], start[order]
            once = np.r_[True, (w[1:] != w[:-1]) | (r[1:] != r[:-1]) | (s[1:] != s[:-1])]  # a repeated row is one document
            w, r, s, d = w[once], r[once], s[once], doc[order][once]
            heads = np.flatnonzero(np.r_[True, w[1:] != w[:-1]])
            sizes = np.diff(np.r_[heads, len(w)])
            n_docs = np.add.reduceat(np.r_[True, (w[1:] != w[:-1]) | (r[1:] != r[:-1])].astype(np.int64), heads)
            least_row, least_start = np.repeat(r[heads], sizes), np.repeat(s[heads], sizes)
            mixed = _mix(r.view(np.uint64) + _mix((s - least_start).astype(np.int64).view(np.uint64), 3), 7)
            occurrences = np.repeat(np.add.reduceat(mixed, heads).view(np.int64), sizes)
            hit = np.repeat(n_docs > 1, sizes)
            if not hit.any():
                continue
            columns = [r, d, s, least_row, least_start, occurrences, np.repeat(n_docs, sizes)]
            by = np.lexsort((s[hit], r[hit]))
            r, d, s, lr, ls, o, n = (x[hit][by] for x in columns)
            new = np.r_[True, (r[1:] != r[:-1]) | (s[1:] != s[:-1] + 1) | (o[1:] != o[:-1]) | (lr[1:] != lr[:-1]) | (ls[1:] != ls[:-1] + 1)]
            head = np.flatnonzero(new)
            tail = np.r_[head[1:], len(r)] - 1
            cut = [r[head], d[head], s[head].astype(np.int32), s[tail].astype(np.int32), lr[head], ls[head].astype(np.int32), o[head], n[head]]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in cut], ["row", "doc_id", "lo", "hi", "least_row", "least_lo", "occurrences", "n_docs"])

    schema = "row bigint, doc_id bigint, lo int, hi int, least_row bigint, least_lo int, occurrences bigint, n_docs bigint"
    runs = extended.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(compare, schema)
    over = Window.partitionBy("row").orderBy("lo")
    last = lambda c: F.lag(c).over(over)
    same = (F.col("lo") == last("hi") + 1) & (F.col("occurrences") == last("occurrences")) & (F.col("least_row") == last("least_row")) & (F.col("lo") - F.col("least_lo") == last("lo") - last("least_lo"))
    marked = runs.withColumn("new", F.when(same, 0).otherwise(1))
    islands = marked.withColumn("island", F.sum("new").over(over.rowsBetween(Window.unboundedPreceding, 0)))
    spans = islands.groupBy("row", "doc_id", "island").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.min("least_lo").alias("least_lo"), F.first("least_row").alias("least_row"), F.first("occurrences").alias("occurrences"), F.first("n_docs").alias("n_docs"))
    passage = F.xxhash64("least_row", "least_lo", "occurrences").alias("passage")
    return spans.select("doc_id", F.col("lo").alias("start_word"), (F.col("hi") - F.col("lo") + threshold).alias("n_words"), passage, "n_docs", "row")


def passage_pairs(shared: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """``a, a_row, a_start, b, b_row, b_start, n_words``: the maximal common spans of every two documents of
    ``shared_passages``, with ``a_row < b_row``.  As many rows as there are pairs: filter ``shared`` first if passages
    are hot."""
    side = lambda x: shared.select("passage", "n_words", F.col("doc_id").alias(x), F.col("row").alias(f"{x}_row"), F.col("start_word").alias(f"{x}_start"))
    pairs = side("a").join(side("b").drop("n_words"), "passage").where("a_row < b_row").withColumn("shift", F.col("b_start") - F.col("a_start"))
    keys = ["a", "a_row", "b", "b_row", "shift"]
    over = Window.partitionBy(*keys).orderBy("a_start")
    follows = F.col("a_start") == F.lag("a_start").over(over) + F.lag("n_words").over(over) - threshold + 1
    islands = pairs.withColumn("new", F.when(follows, 0).otherwise(1)).withColumn("island", F.sum("new").over(over.rowsBetween(Window.unboundedPreceding, 0)))
    spans = islands.groupBy(*keys, "island").agg(F.min("a_start").alias("a_start"), F.min("b_start").alias("b_start"), F.max(F.col("a_start") + F.col("n_words")).alias("end"))
    return spans.select("a", "a_row", "a_start", "b", "b_row", "b_start", (F.col("end") - F.col("a_start")).alias("n_words"))


def repeated_passages(docs: DataFrame, threshold: int = THRESHOLD, seed: int = SEED_WORDS) -> DataFrame:
    """``doc_id, start_word, n_words, partners``: the passages of ``shared_passages`` put together for each document,
    so that every window of a span occurs in another document; ``partners`` are the ids of all documents that share
    some window of it.  A hot passage lists all its documents in each of them."""
    shared = written(shared_passages(docs, threshold, seed), "passages")
    over = Window.partitionBy("row").orderBy("start_word")
    follows = F.col("start_word") == F.lag("start_word").over(over) + F.lag("n_words").over(over) - threshold + 1
    islands = shared.withColumn("new", F.when(follows, 0).otherwise(1)).withColumn("island", F.sum("new").over(over.rowsBetween(Window.unboundedPreceding, 0)))
    members = shared.select("passage", F.col("row").alias("other"), F.col("doc_id").alias("partner")).distinct()
    joined = islands.join(members, "passage").where("row <> other")
    spans = joined.groupBy("row", "doc_id", "island").agg(F.min("start_word").alias("start_word"), F.max(F.col("start_word") + F.col("n_words")).alias("end"), F.array_sort(F.collect_set("partner")).alias("partners"))
    return spans.select("doc_id", "start_word", (F.col("end") - F.col("start_word")).alias("n_words"), "partners")


def op9_repeated_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passages of at least ``THRESHOLD`` words that documents of the whole corpus share, with all their occurrences."""
    return shared_passages(table(spark, sf_dir, "documents"))
