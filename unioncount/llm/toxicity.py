"""Toxic spans by a linear-chain conditional random field over words.

Labels are of documents.  Token labels are derived from them: word forms and stems that occur in many toxic documents
and next to no clean ones mark the tokens of toxic documents.  The field is fitted to these tokens; its forward-backward
marginals give each document a score and the offsets of its toxic spans.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import least_by_hash, table, worker_cache

#: Labelled documents that the field is fitted to: those of each class with the least hash of their id.
FIT_TOXIC, FIT_CLEAN = 1000, 2000
FEATURES = 1 << 18
#: Marginal from which a token belongs to a span.
THRESHOLD = 0.5
#: A form is toxic if it is in so many and in this share of the toxic documents at least, and this many times more often
#: there than in clean ones.
RULES = ((5, 0.008, 50.0), (8, 0.03, 5.0))
#: A clean document that is called toxic weighs as much as so many toxic ones that are missed, when the cut is set.
CLEAN_WEIGHT = 4.0
LANE, EPOCHS = 32, 60
_WORD = re.compile(r"\w+")


def features_of(word: str) -> list[int]:
    """Hashed features: the form, its stems of 4 to 6 letters, its last three, and a constant."""
    forms = [f"w:{word}", "1", f"s:{word[-3:]}", *(f"p:{word[:k]}" for k in (4, 5, 6) if len(word) >= k)]
    return [zlib.crc32(x.encode()) % FEATURES for x in forms]


@dataclass(frozen=True)
class Field:
    """``weights``: of features, for toxic against clean; ``transition[i, j]`` and ``start`` in logs.

    ``cut``: sum of the marginals of likely toxic tokens from which a document is toxic.
    """

    weights: np.ndarray
    transition: np.ndarray
    start: np.ndarray
    cut: float = 0.5

    def emission(self, word: str) -> float:
        return float(self.weights[features_of(word)].sum())


def marginals(emission: np.ndarray, lengths: np.ndarray, transition: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Forward-backward over many documents at once (two states, emissions of state 1 against 0).

    Returns P(state 1) of every token, the log partition of every document, and expected transitions [2, 2] over all.
    Documents are cut into lanes of equal length: lanes are multiplied to 2x2 matrices, these are chained along each
    document, and the messages then run through all lanes side by side.  Exact for any length.
    """
    docs = len(lengths)
    n_lanes = -(-lengths // LANE)
    first = np.cumsum(n_lanes) - n_lanes
    total = int(n_lanes.sum())
    if not total:
        return np.empty(0), np.zeros(docs), np.zeros((2, 2))
    offset = np.cumsum(lengths) - lengths
    inside = np.arange(int(lengths.sum())) - np.repeat(offset, lengths)
    lane, slot = np.repeat(first, lengths) + inside // LANE, inside % LANE
    e = np.zeros((LANE, total))
    live = np.zeros((LANE, total), bool)
    e[slot, lane], live[slot, lane] = emission, True
    e = np.clip(e, -60, 60)
    # state 0 scores 1, state 1 scores exp(e), both scaled by the larger so that nothing overflows
    top = np.maximum(e, 0)
    s0, s1 = np.exp(-top), np.exp(e - top)
    t = np.exp(transition)
    begins = np.zeros(total, bool)
    begins[first[n_lanes > 0]] = True
    # the first token of a document has no transition: the start vector stands in front of it as an identity
    m = np.zeros((2, 2, total))
    m[0, 0] = m[1, 1] = 1
    scale = np.zeros(total)
    for k in range(LANE):
        step = np.where(begins & (k == 0), np.eye(2)[:, :, None], t[:, :, None])
        nxt = np.einsum("abn,bcn->acn", m, step) * np.stack([s0[k], s1[k]])[None]
        m = np.where(live[k], nxt, m)
        if k % 8 == 7:
            z = m.sum((0, 1))
            m /= z
            scale += np.log(z)
    most = int(n_lanes.max())
    head = np.empty((2, total))  # forward message that enters a lane
    logs = np.zeros(docs)
    a = np.tile(np.exp(start)[:, None], docs)
    order = np.argsort(-n_lanes, kind="stable")
    live_docs = np.searchsorted(-n_lanes[order], -np.arange(most), side="left")  # documents with more than j lanes
    for j in range(most):
        d = order[: live_docs[j]]
        x = first[d] + j
        head[:, x] = a[:, d]
        b = np.einsum("an,acn->cn", a[:, d], m[:, :, x])
        z = b.sum(0)
        a[:, d] = b / z
        logs[d] += np.log(z) + scale[x]
    tail = np.empty((2, total))  # backward message that enters a lane from the right
    b = np.ones((2, docs))
    for j in range(most - 1, -1, -1):
        d = order[: live_docs[j]]
        x = first[d] + j
        tail[:, x] = b[:, d]
        c = np.einsum("acn,cn->an", m[:, :, x], b[:, d])
        b[:, d] = c / c.sum(0)
    alpha = np.empty((LANE, 2, total))
    a = head.copy()
    for k in range(LANE):
        step = np.where(begins & (k == 0), np.eye(2)[:, :, None], t[:, :, None])
        nxt = np.einsum("an,acn->cn", a, step) * np.stack([s0[k], s1[k]])
        nxt /= nxt.sum(0)
        a = np.where(live[k], nxt, a)
        alpha[k] = a
    p = np.empty((LANE, total))
    pair = np.zeros((2, 2))
    b = tail.copy()
    for k in range(LANE - 1, -1, -1):
        z = alpha[k] * b
        p[k] = z[1] / z.sum(0)
        s = np.stack([s0[k], s1[k]])
        before = alpha[k - 1] if k else head
        joint = before[:, None] * t[:, :, None] * (s * b)[None]
        ok = live[k] & ~(begins & (k == 0))
        pair += (joint[:, :, ok] / joint[:, :, ok].sum((0, 1))).sum(2)
        nxt = np.einsum("acn,cn->an", np.broadcast_to(t[:, :, None], (2, 2, total)), s * b)
        b = np.where(live[k], nxt / nxt.sum(0), b)
    logs += np.bincount(np.repeat(np.arange(docs), lengths), weights=top[slot, lane], minlength=docs)
    return p[slot, lane], logs, pair


def tokenize(text: str) -> list[str]:
    return [w.lower() for w in _WORD.findall(text)]


def toxic_forms(toxic: list[set[str]], clean: list[set[str]]) -> set[str]:
    """Forms and stems (``stem*``) that tell toxic documents; copies of a document count once."""

    def once(docs: list[set[str]]) -> list[set[str]]:
        near: dict[tuple, list[set[str]]] = {}
        kept = []
        for words in docs:
            signs = [(i, min(zlib.crc32(w.encode(), i) for w in words)) for i in range(6)] if words else []
            if not any(2 * len(words & x) >= len(words | x) for s in signs for x in near.get(s, ())):
                kept.append(words)
                for s in signs:
                    near.setdefault(s, []).append(words)
        return kept

    def count(docs: list[set[str]]) -> Counter:
        found: Counter = Counter()
        for words in docs:
            found.update(words | {w[:k] + "*" for w in words for k in (4, 5, 6) if len(w) > k})
        return found

    toxic, clean = once(toxic), once(clean)
    bad, good = count(toxic), count(clean)
    t, c = max(1, len(toxic)), max(1, len(clean))
    return {x for x, n in bad.items() if any(n >= least and n / t >= share and n / t >= ratio * (good[x] + 0.02) / c for least, share, ratio in RULES)}


def best_cut(scores: np.ndarray, toxic: np.ndarray) -> float:
    """Between two scores of the fitted documents: where missed toxic and wrongly called clean ones cost least."""
    if not toxic.any() or toxic.all():
        return 0.5
    order = np.argsort(-scores, kind="stable")
    s, y = scores[order], toxic[order]
    gain = np.cumsum(y / toxic.sum() - CLEAN_WEIGHT * ~y / (~toxic).sum())
    gain[:-1][s[:-1] == s[1:]] = -np.inf
    i = int(gain.argmax())
    return float(max(0.05, (s[i] + (s[i + 1] if i + 1 < len(s) else 0.0)) / 2))


def fit(toxic: list[str], clean: list[str], epochs: int = EPOCHS, rate: float = 0.4) -> Field:
    """Fit the field to derived token labels by full-batch adaptive gradient steps on the log likelihood."""
    words = [tokenize(x) for x in [*toxic, *clean]]
    forms = toxic_forms([set(x) for x in words[: len(toxic)]], [set(x) for x in words[len(toxic) :]])
    lengths = np.array([len(x) for x in words], np.int64)
    kinds = {w: i for i, w in enumerate(dict.fromkeys(w for x in words for w in x))}
    kind = np.fromiter((kinds[w] for x in words for w in x), np.int64, int(lengths.sum()))
    marked = np.array([w in forms or any(w[:k] + "*" in forms for k in (4, 5, 6) if len(w) > k) for w in kinds], bool)
    label = (marked[kind] if len(kind) else np.zeros(0, bool)) & (np.repeat(np.arange(len(words)), lengths) < len(toxic))
    pairs = [(i, f) for w, i in kinds.items() for f in features_of(w)]
    row, feature = (np.array([x[j] for x in pairs], np.int64) for j in (0, 1))
    weights, transition, start = np.zeros(FEATURES), np.zeros((2, 2)), np.zeros(2)
    heads = np.cumsum(lengths) - lengths
    inner = np.ones(len(kind), bool)
    inner[heads[lengths > 0]] = False
    both = np.zeros((2, 2))
    at = np.flatnonzero(inner)
    np.add.at(both, (label[at - 1].astype(int), label[at].astype(int)), 1)
    squares, squares_t = np.full(FEATURES, 1e-8), np.full((2, 2), 1e-8)
    n = max(1, len(kind))
    truth = np.bincount(kind, weights=label, minlength=len(kinds))
    for _ in range(epochs if len(kind) else 0):
        emission = np.bincount(row, weights=weights[feature], minlength=len(kinds))[kind]
        p, _, pair = marginals(emission, lengths, transition, start)
        by_kind = truth - np.bincount(kind, weights=p, minlength=len(kinds))
        g = np.bincount(feature, weights=by_kind[row], minlength=FEATURES) / n - 1e-7 * weights
        squares += g * g
        weights += rate * g / np.sqrt(squares)
        g = (both - pair) / n - 1e-4 * transition
        squares_t += g * g
        transition += 0.5 * rate * g / np.sqrt(squares_t)
    if not label.any():  # without toxic examples nothing is toxic
        weights[features_of("")[1]] = -40.0
    weights = weights.astype(np.float32)
    emission = np.bincount(row, weights=weights[feature], minlength=len(kinds))[kind] if len(kind) else np.zeros(0)
    p, _, _ = marginals(emission, lengths, transition, start)
    score = np.bincount(np.repeat(np.arange(len(words)), lengths), weights=np.where(p >= THRESHOLD, p, 0), minlength=len(words))
    return Field(weights, transition, start, best_cut(score, np.arange(len(words)) < len(toxic)))


def sample(docs: DataFrame, labels: DataFrame) -> tuple[list[str], list[str]]:
    """Texts of at most ``FIT_TOXIC`` and ``FIT_CLEAN`` labelled documents, whole, in a fixed order."""
    found: tuple[list[str], list[str]] = ([], [])
    for out, value, most in ((found[0], 1, FIT_TOXIC), (found[1], 0, FIT_CLEAN)):
        named = labels.where((F.col("toxic") == value) & F.col("doc_id").isNotNull()).select("doc_id", F.xxhash64("doc_id", F.lit(5)).alias("k")).distinct()
        ids = [r.doc_id for r in least_by_hash(named, F.col("k"), most, "doc_id")]
        if ids:
            rows = docs.where(F.col("doc_id").isin(ids) & F.col("text").isNotNull()).select("doc_id", "text").distinct().collect()
            out += [r.text for r in sorted(rows, key=lambda r: (r.doc_id, r.text))]
    return found


class _Emissions(dict):
    def __init__(self, field: Field) -> None:
        super().__init__()
        self.field = field

    def __missing__(self, word: str) -> float:
        if len(self) >= 1_000_000:
            self.clear()
        value = self[word] = self.field.emission(word.lower())
        return value


def tag(docs: DataFrame, field: Field, threshold: float = THRESHOLD) -> DataFrame:
    """``doc_id, score, peak, toxic, spans`` for every row of ``docs``.

    ``score`` is the sum of the marginals at or over ``threshold``, ``peak`` the greatest marginal; a document is toxic
    if its score reaches the field's cut.  ``spans`` are the character offsets (in the text as
    given, end exclusive) of runs of tokens at or over ``threshold``.  Null, empty and wordless texts score 0; repeated
    rows get equal results; ids that are no whole numbers become null.
    """
    shared = docs.sparkSession.sparkContext.broadcast(field)  # of fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field = shared.value
        cache = worker_cache("toxicity")
        key = (zlib.crc32(field.weights.tobytes()), field.transition.tobytes())
        if cache.get("key") != key:
            cache["key"], cache["emissions"] = key, _Emissions(field)
        get = cache["emissions"].__getitem__
        for whole in batches:
            lo = 0
            texts = [t or "" for t in whole.column("text").to_pylist()]
            sizes = np.cumsum([len(t) for t in texts])
            while lo < len(texts):  # lanes of some million characters at a time
                hi = max(lo + 1, int(np.searchsorted(sizes, (sizes[lo - 1] if lo else 0) + 4_000_000)))
                words = [_WORD.findall(t) for t in texts[lo:hi]]
                lengths = np.array([len(x) for x in words], np.int64)
                emission = np.fromiter((get(w) for x in words for w in x), float, int(lengths.sum()))
                p, _, _ = marginals(emission, lengths, field.transition, field.start)
                ends = np.cumsum(lengths)
                score, peak, spans = [], [], []
                for i, (a, b) in enumerate(zip(ends - lengths, ends)):
                    mine = p[a:b]
                    score.append(float(mine[mine >= threshold].sum()))
                    peak.append(float(mine.max()) if b > a else 0.0)
                    found: list[dict] = []
                    if peak[-1] >= threshold:
                        last = -2
                        for k, match in enumerate(_WORD.finditer(texts[lo + i])):
                            if mine[k] >= threshold:
                                if last == k - 1:
                                    found[-1]["end"] = match.end()
                                else:
                                    found.append({"start": match.start(), "end": match.end()})
                                last = k
                    spans.append(found)
                yield pa.RecordBatch.from_arrays(
                    [whole.column("doc_id").slice(lo, hi - lo), pa.array(np.round(score, 6)), pa.array(np.round(peak, 6)), pa.array([x >= field.cut for x in score]), pa.array(spans, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))],
                    ["doc_id", "score", "peak", "toxic", "spans"],
                )
                lo = hi

    return docs.select(F.col("doc_id").try_cast("bigint").alias("doc_id"), "text").mapInArrow(run, "doc_id bigint, score double, peak double, toxic boolean, spans array<struct<start:int,end:int>>")


def op7_toxic_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores, verdict and offending offsets of every document, by the field that is fitted to the labelled ones."""
    docs = table(spark, sf_dir, "documents")
    return tag(docs, fit(*sample(docs, table(spark, sf_dir, "labels"))))
