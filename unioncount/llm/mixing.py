"""Mixing sources to target weights by pivotal dependent rounding.

Each document of a source gets the same expected number of copies.  The whole part is certain; the fractional parts
are rounded by the pivotal method: two fractional units meet, probability mass moves between them at random until one
is integral, and the other goes on.  Leaves (hash classes of documents) do this on their own and keep at most one
fractional unit a source; a reduction tree combines these, so that each source's total differs from its target by
less than one.
"""

from __future__ import annotations

from collections.abc import Iterator, Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh, table, written

#: Without given weights a source's share of the mix goes with this power of its number of documents.
TEMPER = 0.7
LEAF_ROWS, FAN_IN, SEED = 20_000, 64, 17
#: Probabilities this near to 0 or 1 are integral.
EPS = 1e-9


def expected_copies(docs: DataFrame, weights: Mapping[str, float] | None = None, total: float | None = None, temper: float = TEMPER) -> DataFrame:
    """``source, n, expected``: documents of each source and the copies that each of them is to have on average.

    ``weights`` are relative; a source that they do not name gets 0.  A null source is a source of its own (named by
    null in ``weights``).  ``total`` is the size of the mix, by default the number of documents.
    """
    counts = docs.where("doc_id is not null").groupBy("source").agg(F.count_distinct("doc_id").alias("n"))
    if weights is None:
        weighed = counts.withColumn("w", F.pow(F.col("n").cast("double"), temper))
    else:
        rows = [(k, float(v)) for k, v in weights.items()]
        given = docs.sparkSession.createDataFrame(rows, "given string, w double")
        weighed = counts.join(F.broadcast(given), counts["source"].eqNullSafe(given["given"]), "left").select("source", "n", F.greatest(F.coalesce("w", F.lit(0.0)), F.lit(0.0)).alias("w"))
    sums = weighed.agg(F.sum("w").alias("all_w"), F.sum("n").alias("all_n"))  # one row
    size = F.lit(float(total)) if total is not None else F.col("all_n")
    return weighed.crossJoin(F.broadcast(sums)).select("source", "n", F.coalesce(F.try_divide(F.col("w") * size, F.col("all_w") * F.col("n")), F.lit(0.0)).alias("expected"))


def pivotal(p: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, int]:
    """Round fractional ``p`` one after the other with uniforms ``u``.

    Returns the values, integral but for at most one, and the place of that one (-1 if there is none).
    """
    out = np.array(p, float)
    open_ = -1
    for i in range(len(out)):
        if out[i] <= EPS or out[i] >= 1 - EPS:
            out[i] = round(out[i])
            continue
        if open_ < 0:
            open_ = i
            continue
        a, b = out[open_], out[i]
        s = a + b
        if s < 1:  # one of the two ends at 0
            if u[i] * s < a:
                out[open_], out[i] = s, 0.0
            else:
                out[open_], out[i], open_ = 0.0, s, i
        elif u[i] * (2 - s) < 1 - b:  # one of the two ends at 1
            out[open_], out[i], open_ = 1.0, s - 1, i
        else:
            out[open_], out[i] = s - 1, 1.0
        if out[open_] <= EPS or out[open_] >= 1 - EPS:
            out[open_] = round(out[open_])
            open_ = -1
    return out, open_


_UNIT = "leaf bigint, source string, doc_id bigint, whole bigint, p double, u double, done boolean"


def _round_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pivotal rounding of a partition sorted by (leaf, source, key); a group may go on in the next batch."""
    held: list[pa.RecordBatch] = []
    current = None

    def close() -> Iterator[pa.RecordBatch]:
        whole = pa.Table.from_batches(held).combine_chunks()
        ids = whole.column("doc_id").to_numpy()
        new = np.r_[True, ids[1:] != ids[:-1]]  # repeated rows of an id lie together and are one document
        whole = whole.filter(pa.array(new))
        values, open_ = pivotal(whole.column("p").to_numpy(), whole.column("u").to_numpy())
        done = np.ones(len(values), bool)
        if open_ >= 0:
            done[open_] = False
        whole = whole.set_column(whole.schema.get_field_index("p"), "p", pa.array(values)).set_column(whole.schema.get_field_index("done"), "done", pa.array(done))
        yield from whole.to_batches()

    for batch in batches:
        if not batch.num_rows:
            continue
        leaf, source = batch.column("leaf").to_pylist(), batch.column("source").to_pylist()
        cuts = [0, *(i for i in range(1, len(leaf)) if leaf[i] != leaf[i - 1] or source[i] != source[i - 1]), len(leaf)]
        for lo, hi in zip(cuts, cuts[1:]):
            if held and (leaf[lo], source[lo]) != current:
                yield from close()
                held = []
            current = (leaf[lo], source[lo])
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield from close()


def _pass(units: DataFrame) -> DataFrame:
    ordered = units.repartition("leaf").sortWithinPartitions("leaf", "source", "u", "doc_id")
    return ordered.mapInArrow(_round_groups, _UNIT)


def mix(docs: DataFrame, weights: Mapping[str, float] | None = None, total: float | None = None, temper: float = TEMPER, seed: int = SEED, leaf_rows: int = LEAF_ROWS, fan_in: int = FAN_IN) -> DataFrame:
    """``doc_id, source, copies, expected`` for every document (0 copies included).

    ``copies`` is the floor or the ceiling of ``expected``, has that mean over seeds, and sums in each source to its
    target but for less than 1.  Rows that repeat a ``doc_id`` within a source are one document; rows without an id
    are left out.  The result depends on the rows and the seed alone, neither on their order nor on partitions.
    """
    plan = written(expected_copies(docs, weights, total, temper), "mix-plan")
    n = plan.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    leaves = max(1, -(-int(n) // leaf_rows))
    ids = docs.where(F.col("doc_id").try_cast("bigint").isNotNull()).select(F.col("doc_id").try_cast("bigint").alias("doc_id"), F.col("source").cast("string").alias("source"))
    rate = plan.select(F.col("source").alias("at"), "expected")
    joined = ids.join(rate, ids["source"].eqNullSafe(rate["at"]))
    uniform = (F.xxhash64("doc_id", F.lit(seed)).bitwiseAND(F.lit((1 << 53) - 1))) / float(1 << 53)
    units = joined.select(
        F.pmod(F.xxhash64("doc_id", F.lit(seed + 1)), F.lit(leaves)).alias("leaf"), "source", "doc_id", F.floor("expected").cast("bigint").alias("whole"),
        (F.col("expected") - F.floor("expected")).alias("p"), uniform.alias("u"), F.lit(False).alias("done"),
    )
    rounded = written(_pass(units), "mix-leaves")
    decided = rounded.where("done")
    rest = rounded.where("not done")
    while leaves > 1:
        leaves = -(-leaves // fan_in)
        level = written(_pass(rest.withColumn("leaf", F.floor(F.col("leaf") / fan_in).cast("bigint")).withColumn("u", (F.xxhash64("doc_id", F.lit(seed + 2), F.lit(leaves)).bitwiseAND(F.lit((1 << 53) - 1))) / float(1 << 53))), "mix-level")
        decided = decided.union(level.where("done"))
        rest = level.where("not done")
    last = (F.xxhash64("doc_id", F.lit(seed + 3)).bitwiseAND(F.lit((1 << 53) - 1))) / float(1 << 53)
    decided = decided.union(rest.withColumn("p", F.when(last < F.col("p"), 1.0).otherwise(0.0)))
    out = decided.select("doc_id", "source", (F.col("whole") + F.round("p").cast("bigint")).alias("copies"))
    return out.join(rate, out["source"].eqNullSafe(rate["at"])).select("doc_id", out["source"], "copies", F.round("expected", 9).alias("expected"))


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``doc_id, source, copies, expected`` of every document in a mix whose shares are the tempered sizes of the sources.

    Rows that repeat an id within a source are one document; rows without an id, or with one that is no whole number, are
    left out; null sources are a source; an empty table gives no rows.  See ``mix``.
    """
    return mix(table(spark, sf_dir, "documents"))


def stage_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated by their copies (left out at 0); rows that repeat an id and source all get its copies.

    Rows without an id stay once.
    """
    ident, origin, copies = fresh(docs, "mix_id", "mix_source", "mix_copies")
    plan = mix(docs).where("copies > 0").select(F.col("doc_id").alias(ident), F.col("source").alias(origin), F.col("copies").alias(copies))
    joined = docs.where("doc_id is not null").join(plan, (docs["doc_id"] == plan[ident]) & docs["source"].eqNullSafe(plan[origin]))
    repeated = joined.withColumn(copies, F.explode(F.sequence(F.lit(1), F.col(copies).cast("int")))).select(*[joined[c] for c in docs.columns])
    return repeated.union(docs.where("doc_id is null"))
