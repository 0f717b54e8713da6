"""Nearest neighbours by additive quantisation.

A vector is a sum of codewords, one from each of several codebooks of full dimension.  The codebooks are learned one
after the other on residuals by Lloyd steps over a bounded sample; every vector is encoded, by a beam search that keeps the best
partial sums.  A candidate is scored by table lookups of query-codeword products and the stored norm of its
reconstruction; the best of each block are ranked again by exact distance.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import least_by_hash, ragged, table, written

CODEBOOKS, CODEWORDS, BEAM, STEPS = 16, 256, 4, 2
NEIGHBOURS = 10
#: Vectors that the codebooks are fitted to, at most.
FIT_ROWS = 16_384
#: ``op3_neighbours`` asks for the neighbours of the ids that this divides.
QUERY_STEP = 50
#: Candidates of each block and query that are ranked again by exact distance, at least; a share of the block.
RERANK, RERANK_SHARE = 200, 0.02
#: Vectors of a block: base blocks meet query blocks, so many times as large, in pairs, so that no side is ever broadcast.
BLOCK, QUERY_BLOCKS = 16_384, 4


def clean_vectors(vectors: DataFrame) -> DataFrame:
    """``vec_id, x``: rows with a whole-number id and a vector of the usual dimension without nulls, NaN and infinities; one
    row an id.

    The usual dimension is the most frequent one (the larger of ties).  Of repeated ids the least vector stays.
    """
    rows = vectors.select(F.col("vec_id").try_cast("bigint").alias("vec_id"), F.col("embedding").cast("array<float>").alias("x"))
    fine = rows.where(F.col("vec_id").isNotNull() & (F.size("x") > 0) & ~F.exists("x", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))))
    usual = fine.groupBy(F.size("x").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    return fine.where(F.size("x") == (usual.d if usual else 1)).groupBy("vec_id").agg(F.min("x").alias("x"))


def _matrix(batch, name: str = "x") -> np.ndarray:
    values, off = ragged(batch.column(name))
    return values.astype(np.float32).reshape(len(off) - 1, -1) if len(off) > 1 else np.empty((0, 1), np.float32)


def nearest_codeword(x: np.ndarray, book: np.ndarray) -> np.ndarray:
    return (x @ book.T - 0.5 * (book**2).sum(1)).argmax(1)


def learn(vectors: DataFrame, codebooks: int = CODEBOOKS, codewords: int = CODEWORDS, steps: int = STEPS, rows: int = FIT_ROWS) -> np.ndarray:
    """``[codebooks, codewords, d]``: residual codebooks by Lloyd steps on the driver, over the ``rows`` vectors of the
    least hash of their id (all, if there are fewer).  Every vector is then encoded with them."""
    sample = least_by_hash(vectors, F.xxhash64("vec_id", F.lit(1)), rows, "vec_id")
    rest = np.array([r.x for r in sample], np.float32)
    if not len(rest):
        return np.zeros((codebooks, codewords, 1), np.float32)
    books: list[np.ndarray] = []
    for m in range(codebooks):
        pick = rest[np.random.default_rng(m).permutation(len(rest))[:codewords]]
        book = np.zeros((codewords, rest.shape[1]), np.float32)
        book[: len(pick)] = pick
        for _ in range(steps):
            code = nearest_codeword(rest, book)
            order = np.argsort(code, kind="stable")
            heads = np.flatnonzero(np.r_[True, np.diff(code[order]) != 0])
            book[code[order][heads]] = np.add.reduceat(rest[order].astype(np.float64), heads, axis=0) / np.diff(np.r_[heads, len(code)])[:, None]
        rest = rest - book[nearest_codeword(rest, book)]
        books.append(book)
    return np.stack(books)


def beam_encode(x: np.ndarray, books: np.ndarray, beam: int = BEAM) -> tuple[np.ndarray, np.ndarray]:
    """Codes [n, codebooks] of the least reconstruction error that the beam finds, and the reconstructions."""
    n, d = x.shape
    rest = x[:, None, :].copy()
    codes = np.zeros((n, 1, 0), np.int16)
    for book in books:
        k = len(book)
        norms = (book**2).sum(1)
        cost = rest @ (-2 * book.T)
        cost += norms
        cost += (rest**2).sum(2)[:, :, None]
        flat = cost.reshape(n, -1)
        best = np.empty((n, min(beam, flat.shape[1])), np.int64)
        at = np.arange(n)[:, None]
        for column in best.T:  # a few minima in turn take less than a partition
            column[:] = flat.argmin(1)
            flat[at[:, 0], column] = np.inf
        origin, word = best // k, best % k
        rest = rest[at, origin] - book[word]
        codes = np.concatenate([codes[at, origin], word[:, :, None].astype(np.int16)], axis=2)
    pick = (rest**2).sum(2).argmin(1)
    at = np.arange(n)
    return codes[at, pick], x - rest[at, pick]


def lookup_scores(tables: np.ndarray, codes: np.ndarray, half_norms: np.ndarray) -> np.ndarray:
    """[queries, n]: products of each query with all reconstructions less half their norms: greater is nearer.

    ``tables`` is [codebooks, codewords, queries]: a lookup serves all queries at once."""
    out = np.empty((tables.shape[2], codes.shape[1]), np.float32)
    for lo in range(0, codes.shape[1], 1024):  # what is summed stays in the processor's cache
        first, *rest = codes[:, lo : lo + 1024].astype(np.intp)
        score = tables[0][first]
        score -= half_norms[lo : lo + 1024, None]
        found = np.empty_like(score)
        for table, code in zip(tables[1:], rest, strict=True):
            score += np.take(table, code, axis=0, out=found, mode="clip")
        out[:, lo : lo + 1024] = score.T
    return out


def best_of(scores: np.ndarray, most: int) -> list[np.ndarray]:
    """Of every row the places of its ``most`` greatest scores, and of some more: those above a bound that every 16th
    score gives.  A row of which too few are above it is partitioned."""
    n = scores.shape[1]
    if most >= n:
        return [np.arange(n)] * len(scores)
    some = scores[:, ::16]
    kth = min(some.shape[1], most // 14 + 4)
    bound = np.partition(some, -kth, axis=1)[:, -kth]
    found = [np.flatnonzero(x >= y) for x, y in zip(scores, bound, strict=True)]
    return [x if len(x) >= most else np.argpartition(-y, most - 1)[:most] for x, y in zip(found, scores, strict=True)]


def near_enough(x: np.ndarray, near: np.ndarray, q: np.ndarray, norms: np.ndarray, k: int) -> np.ndarray:
    """Those of ``near`` that may be among the ``k`` nearest to ``q``: all up to the ``k``-th distance in single precision,
    and a margin that is far above its error, so that ties stay."""
    if len(near) <= k:
        return near
    dist = norms[near] - 2 * (x[near] @ q)
    cut = np.partition(dist, k - 1)[k - 1] + np.float32(1e-4) * (norms[near].max() + q @ q)
    return near[dist <= cut] if np.isfinite(cut) else near


def search(vectors: DataFrame, books: np.ndarray, k: int = NEIGHBOURS, rerank: int = RERANK, block: int = BLOCK, queries: DataFrame | None = None) -> DataFrame:
    """``vec_id, neighbour_id, rank, distance``: for every row of ``queries`` (rows of ``vectors``; all of them by default)
    its ``k`` nearest others in ``vectors`` by Euclidean distance.

    Candidates of a query are the best of each block by lookup scores, at least ``rerank`` and ``RERANK_SHARE`` of the
    block: blocks of up to ``rerank`` vectors are so searched exactly, larger ones with a recall that tests hold at 0.9.
    Ties in distance go to the least id.  A table of fewer than ``k + 1`` vectors gives all others.
    """
    queries = vectors if queries is None else queries
    parts, query_parts = (max(1, -(-n // size)) for n, size in ((vectors.count(), block), (queries.count(), QUERY_BLOCKS * block)))
    shared = vectors.sparkSession.sparkContext.broadcast(books)
    code_type = np.uint8 if books.shape[1] <= 256 else np.uint16

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _matrix(batch)
            for lo in range(0, len(x), 256):
                code, near = beam_encode(x[lo : lo + 256], shared.value)
                yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(lo, len(code)) for c in ("vec_id", "x")), pa.array([c.tobytes() for c in code.astype(code_type)], pa.binary()), pa.array(((near**2).sum(1) / 2).astype(np.float32))], ["vec_id", "x", "code", "half_norm"])

    part = lambda n: F.pmod(F.xxhash64("vec_id", F.lit(9)), F.lit(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    coded = written(vectors.select("vec_id", "x").mapInArrow(encode, "vec_id bigint, x array<float>, code binary, half_norm float"), "codes")
    base = coded.select("vec_id", "x", "code", "half_norm", part(parts).alias("b"), each(query_parts).alias("q"), F.lit(True).alias("is_base"))
    asks = queries.select("vec_id", "x", F.lit(None).cast("binary").alias("code"), F.lit(None).cast("float").alias("half_norm"), each(parts).alias("b"), part(query_parts).alias("q"), F.lit(False).alias("is_base"))
    cells = base.union(asks).withColumn("cell", F.col("b").cast("bigint") * query_parts + F.col("q")).drop("b", "q")

    def scan(key, group):
        books = shared.value
        is_base = group.column("is_base").to_numpy()
        stored, asked = group.filter(pa.array(is_base)), group.filter(pa.array(~is_base))
        names = ["vec_id", "neighbour_id", "distance"]
        if not stored.num_rows or not asked.num_rows:
            return pa.table([pa.array([], pa.int64()), pa.array([], pa.int64()), pa.array([], pa.float64())], names)
        stored = stored.sort_by("vec_id")  # candidates don't depend on the order of arrival
        x, ids = _matrix(stored), stored.column("vec_id").to_numpy()
        codes = np.ascontiguousarray(np.frombuffer(b"".join(stored.column("code").to_pylist()), code_type).reshape(len(ids), -1).T)
        half, norms = stored.column("half_norm").to_numpy(), (x**2).sum(1)
        q, qids = _matrix(asked), asked.column("vec_id").to_numpy()
        most = min(len(ids), max(rerank, int(RERANK_SHARE * len(ids)), k + 1))
        found = []
        for lo in range(0, len(q), 128):
            tables = np.ascontiguousarray(np.einsum("qd,mkd->mkq", q[lo : lo + 128], books, optimize=True))
            for i, near in enumerate(best_of(lookup_scores(tables, codes, half), most), lo):
                near = near_enough(x, near[ids[near] != qids[i]], q[i], norms, k)
                dist = ((x[near].astype(np.float64) - q[i]) ** 2).sum(1)
                top = np.lexsort((ids[near], dist))[:k]
                found.append((np.full(len(top), qids[i]), ids[near][top], dist[top]))
        return pa.table([pa.array(np.concatenate(c)) for c in zip(*found)], names)

    from pyspark.sql import Window

    hits = cells.groupBy("cell").applyInArrow(scan, "vec_id bigint, neighbour_id bigint, distance double")
    order = Window.partitionBy("vec_id").orderBy("distance", "neighbour_id")
    ranked = hits.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    return ranked.select("vec_id", "neighbour_id", "rank", F.round(F.sqrt("distance"), 6).alias("distance"))


def op3_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten nearest neighbours, among all vectors of ``embeddings``, of those whose id is divisible by ``QUERY_STEP``."""
    vectors = written(clean_vectors(table(spark, sf_dir, "embeddings")), "vectors")
    return search(vectors, learn(vectors), queries=vectors.where(F.col("vec_id") % QUERY_STEP == 0))
