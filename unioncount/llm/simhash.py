"""Near-duplicate search: 256-bit SimHash fingerprints, BK-trees over shards, groups by star contraction.

A fingerprint is the sign pattern of a sum over the set of a text's words and word pairs.  Shards are cells of random
rotations of that sum (which of its rotated coordinates are the largest); several rotations make a pair within the
radius meet in at least one shard with the wanted recall.  Each shard has a BK-tree (children keyed by their integer
Hamming distance to the parent), and every fingerprint of the shard is a query that follows only edges within the radius
of its distance to the node.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh, ragged, table, whole_groups, word_hashes, written

BITS, WORDS64 = 256, 4
#: Near duplicates differ in at most this many of the 256 bits.
RADIUS = 52
#: The number of rotations gives at least this recall to pairs at the radius itself, and more to nearer ones.
RADIUS_RECALL = 0.9
#: Fingerprints of unrelated texts that are meant to share a shard; sets how fine the cells are.
SHARD_SIZE = 32
#: Chance that the largest of ``n`` rotated coordinates, with its sign, is the same for a pair at ``RADIUS``: simulated
#: (a test does so again).
MEET = {1: 0.798, 2: 0.637, 4: 0.535, 8: 0.460, 16: 0.404, 32: 0.354, 64: 0.311, 128: 0.275, 256: 0.243}
_FP = [f"f{i}" for i in range(WORDS64)]


def _mix(x: np.ndarray, salt: int) -> np.ndarray:
    """A 64-bit finaliser, vectorised."""
    x = x + np.uint64((0x9E3779B97F4A7C15 * (salt + 1)) & (2**64 - 1))
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def feature_sums(words: np.ndarray) -> np.ndarray:
    """``BITS`` sums of signs over a text's features, from the hashes of its words; features are distinct words and pairs."""
    w = words.view(np.uint64)
    features = np.unique(w)
    if len(w) > 1:
        features = np.concatenate([features, np.unique(_mix(w[:-1], 11) + w[1:])])
    total = np.zeros(BITS, np.int64)
    for lo in range(0, len(features), 255):  # byte lanes hold up to 255
        part = features[lo : lo + 255]
        bits = np.unpackbits(np.column_stack([_mix(part, s) for s in range(WORDS64)]).view(np.uint8), axis=1)
        total += bits.view(np.uint64).sum(axis=0, dtype=np.uint64).view(np.uint8)
    return 2 * total - len(features)


def fingerprint(words: np.ndarray) -> np.ndarray:
    """Four 64-bit words of the SimHash of a text: the signs of its sums."""
    return np.packbits(feature_sums(words) > 0).view(np.uint64)


_SIXTEEN = np.array([[(-1.0) ** (i & j).bit_count() for j in range(16)] for i in range(16)], np.float32)


def rotated(sums: np.ndarray, seed: int) -> np.ndarray:
    """Rows turned by random signs and a Hadamard matrix (of 16 x 16 blocks); lengths grow by a constant factor."""
    x = sums.astype(np.float32) * np.random.default_rng(seed).choice(np.array([-1, 1], np.float32), BITS)
    return (_SIXTEEN @ (x.reshape(-1, 16, 16) @ _SIXTEEN)).reshape(-1, BITS)


def cells_of(sums: np.ndarray, groups: tuple[int, ...], rotations: int) -> np.ndarray:
    """``[rows, rotations]``: for each rotation which coordinate of every group is the largest, and its sign."""
    out = np.zeros((len(sums), rotations), np.int32)
    at = np.arange(len(sums))
    for t in range(rotations):
        turned, lo = rotated(sums, t), 0
        for size in groups:
            part = turned[:, lo : lo + size]
            best = np.abs(part).argmax(axis=1)
            out[:, t] = out[:, t] * (2 * size) + 2 * best + (part[at, best] < 0)
            lo += size
    return out


def plan_shards(n: int, shard_size: float = SHARD_SIZE) -> tuple[tuple[int, ...], int]:
    """Groups of rotated coordinates that make a cell, and number of rotations, for ``n`` texts: shards stay small, and
    a pair at ``RADIUS`` shares one with probability ``RADIUS_RECALL`` whatever ``n``."""
    sizes = tuple(MEET)
    ways = [(a,) for a in sizes] + [(128, a) for a in sizes if a <= 128] + [(128, 64, a) for a in sizes if a <= 64] + [(64, 64, 64, a) for a in sizes if a <= 64]
    cells = lambda w: math.prod(2 * a for a in w)
    meet = lambda w: math.prod(MEET[a] for a in w)
    fine = [w for w in ways if cells(w) * shard_size >= n] or [max(ways, key=cells)]
    best = max(fine, key=meet)
    return best, math.ceil(math.log(1 - RADIUS_RECALL) / math.log1p(-meet(best)))


def fingerprints(docs: DataFrame, shard_size: float = SHARD_SIZE) -> DataFrame:
    """``doc_id, text_hash, f0..f3, cells``; rows with a null id or without any word have no fingerprint.

    ``cells`` has the text's cell of each rotation, as many as the number of rows asks for.
    """
    hashed = docs.where(F.col("doc_id").isNotNull()).select("doc_id", F.xxhash64("text").alias("text_hash"), word_hashes(F.col("text")).alias("words")).where(F.size("words") > 0)
    groups, rotations = plan_shards(docs.count(), shard_size)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values, off = ragged(batch.column("words"))
            sums = np.empty((batch.num_rows, BITS), np.int64)
            for i in range(batch.num_rows):
                sums[i] = feature_sums(values[off[i] : off[i + 1]])
            fp = np.packbits(sums > 0, axis=1).view(np.uint64)
            cells = pa.ListArray.from_arrays(pa.array(np.arange(0, len(sums) * rotations + 1, rotations), pa.int32()), pa.array(cells_of(sums, groups, rotations).ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_hash"), *(pa.array(fp[:, j].view(np.int64)) for j in range(WORDS64)), cells], ["doc_id", "text_hash", *_FP, "cells"])

    longs = [T.StructField(c, T.LongType()) for c in ("text_hash", *_FP)]
    return hashed.mapInArrow(run, T.StructType([docs.schema["doc_id"], *longs, T.StructField("cells", T.ArrayType(T.IntegerType()))]))


def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b).sum(axis=1, dtype=np.int64)


class Forest:
    """BK-trees of many shards, built level by level for all shards at once.

    ``node`` rows are fingerprints; ``first_child``..: children of a node sorted by edge, in one array.
    """

    def __init__(self, shard: np.ndarray, fp: np.ndarray) -> None:
        n = len(shard)
        self.fp = fp
        parent, edge = np.full(n, -1), np.zeros(n, np.int64)
        rest = np.arange(n)
        up = np.full(n, -1)  # parent-to-be of a waiting row; roots wait under their shard
        group = np.unique(shard, return_inverse=True)[1].astype(np.int64)
        while len(rest):
            _, first, inverse = np.unique(group, return_index=True, return_inverse=True)
            head = rest[first]
            parent[head] = up[head]
            keep = np.ones(len(rest), bool)
            keep[first] = False
            node = head[inverse]
            rest, node = rest[keep], node[keep]
            edge[rest] = distances(fp[rest], fp[node])
            up[rest] = node
            group = node * (BITS + 1) + edge[rest]
        self.edge = edge
        key = parent * (BITS + 1) + edge
        self.order = np.flatnonzero(parent >= 0)
        self.order = self.order[np.argsort(key[self.order], kind="stable")]
        self.keys = key[self.order]
        roots = np.flatnonzero(parent < 0)
        self.root = np.empty(n, np.int64)
        by = np.argsort(shard[roots], kind="stable")
        self.root = roots[by][np.searchsorted(shard[roots][by], shard)]

    def within(self, radius: int, step: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """``(query, node, distance)`` with query < node, of the same shard, and distance <= radius.

        ``visited`` counts the nodes that the queries meet.
        """
        n, self.visited = len(self.fp), 0
        stack = [(np.arange(lo, min(lo + step, n)), self.root[lo : lo + step]) for lo in range(0, n, step)]
        while stack:
            q, node = stack.pop()
            d = distances(self.fp[q], self.fp[node])
            self.visited += len(q)
            hit = (d <= radius) & (q < node)
            if hit.any():
                yield q[hit], node[hit], d[hit]
            lo = np.searchsorted(self.keys, node * (BITS + 1) + np.maximum(d - radius, 0))
            hi = np.searchsorted(self.keys, node * (BITS + 1) + np.minimum(d + radius, BITS), side="right")
            count = hi - lo
            q, lo, count = q[count > 0], lo[count > 0], count[count > 0]
            ends = np.cumsum(count)
            i = 0
            while i < len(q):  # bounded slices of the frontier
                j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + step)))
                c = count[i:j]
                flat = np.arange(c.sum()) - np.repeat(np.cumsum(c) - c, c) + np.repeat(lo[i:j], c)
                stack.append((np.repeat(q[i:j], c), self.order[flat]))
                i = j


def near_edges(distinct: DataFrame, radius: int = RADIUS) -> DataFrame:
    """``a, b``: for each shard, links that join the fingerprints within the radius of each other (``a < b`` by id)."""
    long = T.LongType()
    rows = distinct.select("rep", *_FP, F.posexplode("cells").alias("t", "cell")).select(F.xxhash64("t", "cell").alias("shard"), "rep", *_FP)

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in whole_groups(batches, "shard"):
            shard, rep = group.column("shard").to_numpy(), group.column("rep").to_numpy()
            start = np.flatnonzero(np.r_[True, shard[1:] != shard[:-1]])
            alone = np.diff(np.r_[start, len(shard)]) == 1
            busy = np.ones(len(shard), bool)
            busy[start[alone]] = False
            if not busy.any():
                continue
            shard, rep = shard[busy], rep[busy]
            fp = np.column_stack([group.column(c).to_numpy()[busy] for c in _FP]).view(np.uint64)
            label = np.arange(len(rep))
            for q, node, _ in Forest(shard, fp).within(radius):
                link(label, q, node)
            root = settle(label)
            least = np.full(len(rep), np.iinfo(np.int64).max)
            np.minimum.at(least, root, rep)
            a = least[root]
            some = a != rep
            yield pa.RecordBatch.from_arrays([pa.array(a[some]), pa.array(rep[some])], ["a", "b"])

    sharded = rows.repartition("shard").sortWithinPartitions("shard")
    return sharded.mapInArrow(search, T.StructType([T.StructField("a", long), T.StructField("b", long)])).distinct()


def settle(label: np.ndarray) -> np.ndarray:
    while (label[label] != label).any():
        label[:] = label[label]
    return label


def link(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Join the groups of each ``a[i]`` and ``b[i]``; labels point to the least index."""
    while True:
        settle(label)
        x, y = label[a], label[b]
        apart = x != y
        if not apart.any():
            return
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))


def components(edges: DataFrame) -> DataFrame:
    """``node, root`` for every node of ``edges (a, b)``: the least id of its group.

    Alternating large-star and small-star contraction; each round is grouped aggregation over the edges, its result
    written to the shared folder.  Ends when a round changes nothing.
    """
    from pyspark.sql import Window

    cur = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
    seen = None
    while True:
        over = Window.partitionBy("u")
        both = cur.union(cur.select(F.col("v"), F.col("u"))).toDF("u", "v")
        large = both.withColumn("m", F.least("u", F.min("v").over(over))).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.withColumn("m", F.min("v").over(over))
        small = least.select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        cur = written(small, "edges")
        state = tuple(cur.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.bit_xor(F.xxhash64("v", "u"))).first())
        if state == seen or not state[0]:
            return cur.select(F.col("u").alias("node"), F.col("v").alias("root")).union(cur.select(F.col("v"), F.col("v")).distinct())
        seen = state


def near_duplicates(docs: DataFrame, radius: int = RADIUS, shard_size: float = SHARD_SIZE) -> DataFrame:
    """``doc_id, keep_id, text_hash, keep_text_hash``: every document of a near-duplicate group but its least, with that.

    A document is an id and a text (``text_hash``): rows that repeat both are one document, other texts under the same
    id are documents of their own.  Groups are the connected components of pairs within ``radius`` bits; the least
    document has the least id, then fingerprint, then text hash.  Texts without words and rows without id belong to no
    group.  Equal fingerprints are distance 0.
    """
    fps = written(fingerprints(docs, shard_size), "simhash")
    least = F.min(F.struct("doc_id", "text_hash", "cells")).alias("least")
    # nodes are numbered in the order of their least document, and written, so that the numbers stay
    numbered = fps.groupBy(*_FP).agg(least).orderBy("least.doc_id", *_FP).select(F.monotonically_increasing_id().alias("rep"), "least", *_FP)
    distinct = written(numbered, "simhash-distinct")
    groups = components(near_edges(distinct.select("rep", *_FP, F.col("least.cells").alias("cells")), radius))
    roots = distinct.join(groups, F.col("rep") == F.col("node"), "left").select(*_FP, F.coalesce("root", "rep").alias("root"))
    keep = distinct.select(F.col("rep").alias("root"), F.col("least.doc_id").alias("keep_id"), F.col("least.text_hash").alias("keep_text_hash"))
    found = fps.drop("cells").join(roots.join(keep, "root"), _FP).where("doc_id <> keep_id or text_hash <> keep_text_hash")
    return found.select("doc_id", "keep_id", "text_hash", "keep_text_hash").distinct()


def op4_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate documents of the whole corpus with the document of their group that stays."""
    return near_duplicates(table(spark, sf_dir, "documents"))


def stage_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group stays: the least id; documents without id or words all stay.  Rows are
    dropped by id and text, so another text under the same id stays."""
    drop = near_duplicates(docs)
    ident, text = fresh(docs, "near_drop_id", "near_drop_text")
    drop = drop.select(F.col("doc_id").alias(ident), F.col("text_hash").alias(text)).distinct()
    return docs.join(drop, (docs["doc_id"] == drop[ident]) & (F.xxhash64(docs["text"]) == drop[text]), "left_anti")
