"""Language ID by Bayesian evidence fusion.

Evidence of a row: hashed byte-trigram likelihoods of its whole text, the language that its markup declares, the
suffix of its address, and a prior of its host that is smoothed towards its domain and the whole corpus.  The text
model is fitted on a bounded sample of labelled rows (``FIT_ROWS`` a language); every other table of evidence is a
grouped aggregation of the text posteriors over all rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh, table, written

BUCKETS = 1 << 16
#: Labelled rows for each language that the text model is fitted on: those with the least hash of their id.
FIT_ROWS = 400
UNKNOWN = "und"
#: Neighbouring trigrams depend on each other: n of them count as n E / (n + E) independent ones, so a text as E at most.
TEXT_EVIDENCE = 60.0
#: Pseudo-counts that tie a host to its domain, and a domain to the corpus.
HOST_PULL, DOMAIN_PULL = 5.0, 20.0
PRIOR_UNKNOWN = 1e-3
MIN_POSTERIOR = 0.5


@dataclass(frozen=True)
class TextModel:
    """``table``: float32 [BUCKETS, languages + 1] of log likelihoods; the last column is the unknown language."""

    languages: tuple[str, ...]
    table: np.ndarray


def trigram_codes(data: np.ndarray) -> np.ndarray:
    """Hashed codes of the byte trigrams that start at each byte but the last two."""
    b = data.astype(np.uint32)
    return ((b[:-2] * np.uint32(0x9E3779B1) + b[1:-1] * np.uint32(0x85EBCA6B) + b[2:] * np.uint32(0xC2B2AE35)) >> np.uint32(16)).astype(np.uint16)


def letters_of(text: Column) -> Column:
    """Lower-cased letters; addresses, digits and signs say nothing of a language.  What touches them stays, as a
    language written without blanks is one run with them."""
    return F.regexp_replace(F.lower(text), r"(?:https?://|www\.)[!-~]+|[a-z0-9._%+-]*@[a-z0-9.-]+|[^\p{L}]+", " ")


def fit_text_model(spark: SparkSession, docs: DataFrame, fit_rows: int = FIT_ROWS) -> TextModel:
    """Multinomial model of hashed trigrams from at most ``fit_rows`` labelled rows a language."""
    labelled = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    key = F.xxhash64("doc_id", F.lit(7))
    # the aggregate keeps only ids and hashes; the texts are fetched for the chosen few
    ranked = labelled.select("lang", "doc_id", key.alias("k")).distinct()
    from pyspark.sql import Window

    chosen = ranked.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy("k", "doc_id"))).where(F.col("r") <= fit_rows)
    ids = [r.doc_id for r in chosen.select("doc_id").collect()]  # at most fit_rows a language
    rows = labelled.where(F.col("doc_id").isin(ids)).select("lang", letters_of(F.col("text")).alias("t")).collect() if ids else []
    languages = tuple(sorted({r.lang for r in rows}))
    counts = np.zeros((BUCKETS, len(languages) + 1))
    for r in rows:
        data = np.frombuffer(r.t.encode(), np.uint8)
        if len(data) > 2:
            counts[:, languages.index(r.lang)] += np.bincount(trigram_codes(data), minlength=BUCKETS)
    smooth = 0.05
    like = np.log((counts + smooth) / (counts.sum(0) + smooth * BUCKETS))
    like[:, -1] = -np.log(BUCKETS)
    return TextModel(languages, like.astype(np.float32))


def score_texts(column: pa.Array, model: TextModel, step: int = 2_000_000) -> tuple[np.ndarray, np.ndarray]:
    """Log likelihoods [rows, languages + 1] and trigram counts of whole texts; 0 trigrams for null and tiny texts."""
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    off = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    n = np.maximum(np.diff(off) - 2, 0)
    if column.null_count:
        n = np.where(column.is_valid().to_numpy(zero_copy_only=False), n, 0)
    out = np.zeros((len(column), model.table.shape[1]))
    if not n.any():
        return out, n
    data = np.frombuffer(column.buffers()[2], np.uint8)
    rows = np.flatnonzero(n)
    i = 0
    while i < len(rows):  # as many whole rows at a time as fit the step; one long text may exceed it
        j = max(i + 1, int(np.searchsorted(off[rows], off[rows[i]] + step)))
        part = rows[i:j]
        lo, hi = off[part[0]], off[part[-1]] + n[part[-1]] + 2
        scores = np.vstack([model.table[trigram_codes(data[lo:hi])], np.zeros((1, model.table.shape[1]), np.float32)])
        cuts = np.column_stack([off[part] - lo, off[part] - lo + n[part]]).ravel()
        out[part] = np.add.reduceat(scores, cuts, axis=0, dtype=np.float64)[::2]
        i = j
    return out, n


def _host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1))


def page_text(html: Column) -> Column:
    bare = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->|<[^>]*>", " ")
    return F.regexp_replace(bare, r"&[#a-zA-Z0-9]{1,10};", " ")


def evidence_of_pages(pages: DataFrame) -> DataFrame:
    """``page_id, text, host, domain, suffix, declared`` of web pages; what is absent is null."""
    host = _host(F.col("url"))
    declared = F.lower(F.regexp_extract("html", r"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?([a-zA-Z]{2,3})", 1))
    blank = lambda c: F.when(c != "", c)
    return pages.select(
        "page_id", page_text(F.col("html")).alias("text"), blank(host).alias("host"),
        blank(F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1)).alias("domain"), blank(F.regexp_extract(host, r"\.([a-z]+)$", 1)).alias("suffix"), blank(declared).alias("declared"),
    )


def classify(rows: DataFrame, model: TextModel, min_posterior: float = MIN_POSTERIOR) -> DataFrame:
    """Posterior language of every row of ``rows (ids..., text, host, domain, suffix, declared)``.

    Returns the id columns with ``language, posterior, text_language, rejected``.  A row is rejected if no language
    reaches ``min_posterior`` or the unknown language leads.  Null, empty and letterless texts bring no evidence of
    their own and are rejected, whatever their host says.  Repeated rows get equal results.
    """
    langs = [*model.languages, UNKNOWN]
    ids = [c for c in rows.columns if c not in ("text", "host", "domain", "suffix", "declared")]
    k = len(langs)
    prior = np.log(np.array([(1 - PRIOR_UNKNOWN) / max(1, k - 1)] * (k - 1) + [PRIOR_UNKNOWN]))
    carried = [*ids, "host", "domain", "suffix", "declared"]
    shared = rows.sparkSession.sparkContext.broadcast(model)  # of fixed size: BUCKETS x languages

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            like, n = score_texts(batch.column("letters"), shared.value)
            seen = (n > 0) & (pc.binary_length(pc.utf8_trim_whitespace(batch.column("letters"))).fill_null(0).to_numpy(zero_copy_only=False) > 0)
            like *= (TEXT_EVIDENCE / (n + TEXT_EVIDENCE))[:, None]
            like[~seen] = 0
            soft = like + prior
            soft = np.exp(soft - soft.max(1, keepdims=True))
            soft /= soft.sum(1, keepdims=True)
            lists = [pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, k), pa.int32()), pa.array(x.ravel(), pa.float64())) for x in (like, soft)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in carried), *lists, pa.array(seen)], [*carried, "like", "soft", "seen"])

    schema = T.StructType([*(rows.schema[c] for c in carried), T.StructField("like", T.ArrayType(T.DoubleType())), T.StructField("soft", T.ArrayType(T.DoubleType())), T.StructField("seen", T.BooleanType())])
    scored = written(rows.select(*carried, letters_of(F.col("text")).alias("letters")).mapInArrow(score, schema), "langid")

    def sums(by: str) -> DataFrame:
        some = scored.where(F.col(by).isNotNull() & F.col("seen"))
        # written, so that the size is known when the join is planned: a small table is broadcast, and no row with a
        # frequent or absent host is shuffled; a large one is joined by host
        return written(some.groupBy(by).agg(F.array(*[F.sum(F.col("soft")[i]) for i in range(k)]).alias(f"{by}_n")), f"langid-{by}")

    base = scored.where("seen").agg(*[F.coalesce(F.sum(F.col("soft")[i]), F.lit(0.0)).alias(f"c{i}") for i in range(k)]).first()
    total = np.array([float(x) for x in base])
    share = (total + 1.0) / (total.sum() + k)
    none = F.array(*[F.lit(0.0)] * k)
    const = lambda xs: F.array(*[F.lit(float(x)) for x in xs])
    fused = scored
    for by in ("declared", "suffix", "domain", "host"):
        # rows without the key match nothing; keys of their own keep them from meeting in one task
        counts = sums(by).withColumnRenamed(by, "key__")
        spread = F.concat(F.lit("\0"), F.pmod(F.xxhash64(*ids, "like"), F.lit(4096)).cast("string"))
        fused = fused.join(counts, F.coalesce(F.col(by), spread) == F.col("key__"), "left").drop("key__")
    own = F.when(F.col("seen"), F.col("soft")).otherwise(none)
    # leave-one-out: a row's own text must not come back to it as the prior of its host
    less = lambda c: F.zip_with(F.coalesce(F.col(c), none), F.when(F.col(c).isNull(), none).otherwise(own), lambda a, b: F.greatest(a - b, F.lit(0.0)))
    pull = lambda n, parent, weight: F.zip_with(n, parent, lambda a, p: (a + weight * p) / (F.aggregate(n, F.lit(0.0), lambda s, x: s + x) + weight))
    fused = fused.withColumn("p_domain", pull(less("domain_n"), const(share), DOMAIN_PULL))
    fused = fused.withColumn("p_host", pull(less("host_n"), F.col("p_domain"), HOST_PULL))
    # P(tag | language), up to a factor that all languages share: counts of the tag, smoothed by the share of the language,
    # over those of the language; a tag that no other row has says nothing
    tag = lambda c: F.zip_with(F.zip_with(less(c), const(share), lambda a, p: a + p), const(total), lambda a, t: F.log(a / (t + 1.0)))
    logs = F.zip_with(F.zip_with(F.col("like"), F.col("p_host"), lambda a, p: a + F.log(p)), F.zip_with(tag("declared_n"), tag("suffix_n"), lambda a, b: a + b), lambda a, b: a + b)
    fused = fused.withColumn("logs", logs).withColumn("top", F.array_max("logs"))
    fused = fused.withColumn("z", F.aggregate(F.transform("logs", lambda x: F.exp(x - F.col("top"))), F.lit(0.0), lambda s, x: s + x))
    names = F.array(*[F.lit(x) for x in langs])
    pick = lambda c: F.element_at(names, F.array_position(F.col(c), F.array_max(c)).cast("int"))
    best = fused.select(*ids, pick("logs").alias("language"), (1.0 / F.col("z")).alias("posterior"), F.when(F.col("seen"), pick("soft")).otherwise(UNKNOWN).alias("text_language"), "seen")
    reject = ~F.col("seen") | (F.col("language") == UNKNOWN) | (F.col("posterior") < min_posterior)
    return best.select(*ids, "language", F.round("posterior", 6).alias("posterior"), "text_language", reject.alias("rejected"))


def evidence_of_documents(docs: DataFrame) -> DataFrame:
    """Documents have no address: their source stands for the host, and nothing is declared."""
    void = F.lit(None).cast("string")
    return docs.select("doc_id", "text", F.col("source").alias("host"), void.alias("domain"), void.alias("suffix"), void.alias("declared"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of every document and every page: ``doc_id`` or ``page_id`` with the fused posterior."""
    docs = table(spark, sf_dir, "documents")
    model = fit_text_model(spark, docs)
    documents = evidence_of_documents(docs).withColumn("page_id", F.lit(None).cast("bigint"))
    pages = evidence_of_pages(table(spark, sf_dir, "pages")).withColumn("doc_id", F.lit(None).cast("bigint"))
    return classify(documents.unionByName(pages), model)


def stage_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the documents whose language is known; columns as given.  Rows of one id, or without id, are kept or dropped
    by their own text and source."""
    key, ident, bad_key = fresh(docs, "langid_key", "langid_id", "langid_bad")
    model = fit_text_model(spark, docs)
    keyed = docs.withColumn(key, F.xxhash64("text", F.lit(1), "source"))
    verdict = classify(keyed.select("doc_id", key, "text", F.col("source").alias("host"), *[F.lit(None).cast("string").alias(c) for c in ("domain", "suffix", "declared")]), model)
    bad = verdict.where("rejected").select(F.col("doc_id").alias(ident), F.col(key).alias(bad_key)).distinct()
    return keyed.join(bad, F.col("doc_id").eqNullSafe(F.col(ident)) & (F.col(key) == F.col(bad_key)), "left_anti").select(*docs.columns)
