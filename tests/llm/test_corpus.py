"""Corpus operators against brute force, exact round trips and held-out accuracy, and on awkward tables."""

from __future__ import annotations

import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from unioncount.llm import ann, grace_dedup, langid, mixing, packing, simhash, substrings, token_counts, token_store, tokens, toxicity
from unioncount.llm.common import table, written

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"
RNG = random.Random(4)
WORDS = ["".join(RNG.choice("abcdefghijklmnop") for _ in range(RNG.randint(2, 9))) for _ in range(4000)]


def prose(n: int, seed: int) -> str:
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) for _ in range(n))


def awkward_rows() -> list[tuple]:
    """Nulls in every column, empty and very long texts, ties, repeated rows."""
    long = prose(60_000, 1)
    return [
        (1, prose(120, 2), "en", "a", 5), (2, prose(120, 2), "en", "a", 5), (2, prose(120, 2), "en", "a", 5), (3, None, "en", "a", None), (4, None, None, None, None),
        (5, "", "en", "b", 0), (6, "", "fr", "b", 0), (None, prose(70, 3), "en", "a", 1), (7, long, "en", "b", 1), (8, long + " end", "en", None, 1), (9, "   ", "en", "b", 3),
        (10, "!!! ??? 123", None, "b", 3), (11, "x", "en", "b", 1), (12, prose(120, 2) + " tail", "en", "c", 1), (13, "日本語のテキスト", "en", "c", 1),
    ]


@pytest.fixture(scope="module")
def awkward(spark):
    # extra columns whose names clash with those that operators use inside
    return written(spark.createDataFrame(awkward_rows(), DOCS).withColumn("content_hash", F.lit(1)).withColumn("mix_id", F.lit("x")).withColumn("near_drop_id", F.lit(0)).withColumn("langid_key", F.lit(2)).withColumn("rank", F.lit(None).cast("int")).withColumn("Salt", F.lit(3)), "awkward")


@pytest.fixture(scope="module")
def docs(spark, small_dir):
    return table(spark, small_dir, "documents")


def empty(spark):
    return spark.createDataFrame([], DOCS)


# exact dedup


def test_exact_keeps_least_id_of_each_text(docs):
    rows = docs.select("doc_id", "text").collect()
    want: dict[str, int] = {}
    for r in rows:
        want[r.text] = min(want.get(r.text, 1 << 60), r.doc_id)
    for limit in (grace_dedup.BUCKET_BYTES, 20_000):  # the small bucket makes several levels of spill files
        got = grace_dedup.exact_dedup(docs, limit).select("doc_id", "text").collect()
        assert {(r.text, r.doc_id) for r in got} == {(t, i) for t, i in want.items()} and len(got) == len(want)


def test_exact_awkward(spark, awkward):
    got = grace_dedup.exact_dedup(awkward)
    assert got.columns == awkward.columns
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in got.collect()) == [(False, x) for x in (1, 3, 5, 7, 8, 9, 10, 11, 12, 13)] + [(True, 0)]
    assert grace_dedup.exact_dedup(empty(spark)).count() == 0


def test_table_compares_contents_under_equal_hashes():
    seen = grace_dedup.ContentTable(4)
    for i in range(50):
        e = seen.find(7, b"%d" % i)
        assert e < 0
        seen.add(-1 - e, 7, b"%d" % i, (False, i, 0))
    assert [seen.find(7, b"%d" % i) for i in range(50)] == list(range(50)) and seen.find(7, b"x") < 0


def test_combine_keeps_what_may_win():
    import pyarrow as pa

    batch = pa.RecordBatch.from_pydict({"doc_id": [5, 3, 4, None], "text": ["a", "a", "a", "a"], "h": [1, 1, 1, 1], "t": [0, 0, 0, 0]})
    assert next(grace_dedup.combine(iter([batch]), "h", "t")).column("doc_id").to_pylist() == [5, 3]


# near dedup


def near_brute(fps: np.ndarray, radius: int) -> set[tuple[int, int]]:
    return {(i, i + 1 + int(j)) for i in range(len(fps)) for j in np.flatnonzero(simhash.distances(fps[i + 1 :], fps[i]) <= radius)}


def test_forest_equals_brute_force():
    rng = np.random.default_rng(0)
    base = rng.integers(0, 2**63, (60, 4), dtype=np.uint64)
    fps = np.repeat(base, 5, axis=0)
    for _ in range(12):
        fps[np.arange(300), rng.integers(0, 4, 300)] ^= np.uint64(1) << rng.integers(0, 63, 300).astype(np.uint64)
    shard = rng.integers(0, 3, 300)
    want = {(a, b) for a, b in near_brute(fps, 20) if shard[a] == shard[b]}
    got = {(int(a), int(b)) for q, n, _ in simhash.Forest(shard, fps).within(20, step=64) for a, b in zip(q, n)}
    assert got == want and want


def test_components_equal_union_find(spark):
    rng = random.Random(1)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1040)]
    label = {x: x for e in edges for x in e}
    for _ in range(400):
        for a, b in edges:
            label[a] = label[b] = min(label[a], label[b])
    got = {r.node: r.root for r in simhash.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == {x: y for x, y in label.items() if x in got} and all(x == label[x] for x in label if x not in got)


def test_near_recall_against_brute_force(docs):
    fps = simhash.fingerprints(docs).toPandas().sort_values("doc_id")
    ids, f = fps["doc_id"].to_numpy(), fps[["f0", "f1", "f2", "f3"]].to_numpy().view(np.uint64)
    pairs = near_brute(f, simhash.RADIUS)
    root = {r.doc_id: r.keep_id for r in simhash.near_duplicates(docs).collect()}
    hit = [root.get(ids[a], ids[a]) == root.get(ids[b], ids[b]) for a, b in pairs]
    assert len(hit) > 100 and np.mean(hit) >= 0.95


def test_near_copies_are_caught_and_others_stay(spark):
    rows = []
    for i in range(60):
        words = prose(150, 100 + i).split()
        rows.append((2 * i, " ".join(words), "en", "a", 1))
        for j in random.Random(i).sample(range(150), 6):
            words[j] = "changed"
        rows.append((2 * i + 1, " ".join(words), "en", "a", 1))
    got = {r.doc_id: r.keep_id for r in simhash.near_duplicates(spark.createDataFrame(rows, DOCS)).collect()}
    assert len(got) >= 57 and all(a == b + 1 and b % 2 == 0 for a, b in got.items())


def test_near_awkward(spark, awkward):
    got = simhash.stage_near(spark, awkward, "")
    assert got.columns == awkward.columns
    kept = Counter(r.doc_id for r in got.collect())
    assert kept == Counter([1, 3, 4, 5, 6, None, 7, 9, 10, 11, 13])
    assert simhash.stage_near(spark, empty(spark), "").count() == 0


def pairs_at_the_radius(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Sums of two texts whose signs differ in ``RADIUS`` places."""
    rng = np.random.default_rng(11)
    near = np.cos(np.pi * simhash.RADIUS / simhash.BITS)
    x = rng.normal(size=(n, simhash.BITS))
    y = near * x + np.sqrt(1 - near**2) * rng.normal(size=x.shape)
    at = ((x > 0) != (y > 0)).sum(1) == simhash.RADIUS
    return x[at], y[at]


def test_chances_of_sharing_a_cell():
    x, y = pairs_at_the_radius(30_000)
    for size, p in simhash.MEET.items():
        met = (simhash.cells_of(x, (size,), 8) == simhash.cells_of(y, (size,), 8)).mean()
        assert abs(met - p) < 0.02, size


@pytest.mark.parametrize("n", [1, 100, 1000, 10**4, 250_000, 10**6, 10**7, 10**9, 10**10])
def test_recall_at_the_radius_at_every_size(n):
    groups, rotations = simhash.plan_shards(n)
    x, y = pairs_at_the_radius(30_000 if n < 10**8 else 8_000)
    met = (simhash.cells_of(x, groups, rotations) == simhash.cells_of(y, groups, rotations)).any(axis=1).mean()
    assert met > 0.87, (n, groups, rotations)  # 0.9 but for the error of some hundred pairs
    assert rotations < 6 * max(2, n) ** 0.17


def test_trees_leave_out_what_the_radius_excludes():
    rng = np.random.default_rng(5)
    centres = rng.integers(0, 2**63, (40, 4), dtype=np.uint64)
    fps = np.repeat(centres, 20, axis=0)
    for _ in range(6):
        fps[np.arange(800), rng.integers(0, 4, 800)] ^= np.uint64(1) << rng.integers(0, 63, 800).astype(np.uint64)
    forest = simhash.Forest(np.zeros(800, np.int64), fps)
    found = {(int(a), int(b)) for q, n, _ in forest.within(4) for a, b in zip(q, n)}
    assert found == near_brute(fps, 4) and forest.visited < 0.6 * 800 * 800


def test_texts_under_one_id_are_documents_of_their_own(spark):
    p, q = prose(150, 1).split(), prose(150, 2).split()
    near = lambda w: " ".join(["changed", *w[1:70], "too", *w[71:]])
    p, q, near_p, near_q = " ".join(p), " ".join(q), near(p), near(q)
    rows = [(3, p, "en", "a", 1), (3, q, "en", "a", 1), (1, near_q, "en", "a", 1), (9, near_p, "en", "a", 1), (3, p, "en", "b", 1), (5, near(prose(150, 7).split()), "en", "a", 1), (5, prose(150, 7), "en", "a", 1)]
    got = simhash.stage_near(spark, spark.createDataFrame(rows, DOCS), "").collect()
    kept = Counter((r.doc_id, r.text) for r in got)
    assert kept[3, p] == 2 and kept[1, near_q] == 1 and sum(v for (i, _), v in kept.items() if i == 5) == 1 and len(got) == 4


# language


def test_rows_without_id_are_judged_by_their_text(spark, docs):
    some = docs.limit(200).withColumn("doc_id", F.when(F.col("doc_id") % 2 == 0, F.col("doc_id")))
    extra = spark.createDataFrame([(None, "!!! 123", "en", "a", 7), (None, None, "en", "a", 0)], DOCS)
    some = written(some.unionByName(extra), "no-id")
    got = langid.stage_language(spark, some, "")
    assert got.where("doc_id is null").count() == some.where("doc_id is null").count() - 2
    assert not {r.text for r in got.collect()} & {"!!! 123", None}


def test_a_language_without_blanks_keeps_its_evidence(spark, docs):
    r = random.Random(8)
    signs = [chr(0x4E00 + i) for i in range(300)]
    rows = [(100_000 + i, "".join(r.choice(signs) for _ in range(60)) + str(i) + "".join(r.choice(signs) for _ in range(60)), "zz", "s", 1) for i in range(80)]
    got = langid.stage_language(spark, docs.limit(200).unionByName(spark.createDataFrame(rows, DOCS)), "")
    assert got.where("lang = 'zz'").count() == 80
    letters = spark.createDataFrame([("甲乙2024丙 a@b.org丁 see https://x.org/a1戊",)], "t string").select(langid.letters_of(F.col("t"))).first()[0]
    assert letters.split() == ["甲乙", "丙", "丁", "see", "戊"]


def test_language_held_out(spark, docs):
    model = langid.fit_text_model(spark, docs.where("doc_id % 2 = 0"), 60)
    rest = docs.where("doc_id % 2 = 1")
    got = langid.classify(langid.evidence_of_documents(rest), model).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert np.mean([r.language == r.lang for r in got]) > 0.98 and np.mean([r.rejected for r in got]) < 0.005


def test_scores_equal_plain_sums(spark, docs):
    import pyarrow as pa

    model = langid.fit_text_model(spark, docs, 20)
    texts = ["abc", None, "", "ab", "the rest of the text", "é" * 5000]
    got, n = langid.score_texts(pa.array(texts), model, step=64)
    for t, row, k in zip(texts, got, n, strict=True):
        b = (t or "").encode()
        want = sum((model.table[langid.trigram_codes(np.frombuffer(b[i : i + 3], np.uint8))[0]].astype(float) for i in range(len(b) - 2)), np.zeros(model.table.shape[1]))
        assert np.allclose(row, want, rtol=1e-5) and k == max(0, len(b) - 2)


def fused_brute(rows: list, model, texts: list[str]) -> list[tuple]:
    """Posterior of every row by plain sums over all the others."""
    import pyarrow as pa

    langs = [*model.languages, langid.UNKNOWN]
    k = len(langs)
    prior = np.log(np.array([(1 - langid.PRIOR_UNKNOWN) / (k - 1)] * (k - 1) + [langid.PRIOR_UNKNOWN]))
    like, n = langid.score_texts(pa.array(texts), model)
    like *= (langid.TEXT_EVIDENCE / (n + langid.TEXT_EVIDENCE))[:, None]
    seen = np.array([bool((t or "").strip()) and m > 0 for t, m in zip(texts, n)])
    like[~seen] = 0
    soft = np.exp(like + prior - (like + prior).max(1, keepdims=True))
    soft /= soft.sum(1, keepdims=True)
    total = soft[seen].sum(0)
    share = (total + 1) / (total.sum() + k)
    out = []
    for i, r in enumerate(rows):
        def others(by):
            at = [j for j, x in enumerate(rows) if seen[j] and r[by] is not None and x[by] == r[by] and j != i]
            return soft[at].sum(0) if at else np.zeros(k)

        domain, host = others("domain"), others("host")
        p = (domain + langid.DOMAIN_PULL * share) / (domain.sum() + langid.DOMAIN_PULL)
        p = (host + langid.HOST_PULL * p) / (host.sum() + langid.HOST_PULL)
        logs = like[i] + np.log(p)
        for by in ("declared", "suffix"):
            logs = logs + np.log((others(by) + share) / (total + 1))
        post = np.exp(logs - logs.max())
        post /= post.sum()
        best = int(post.argmax())
        out.append((langs[best], post[best], not seen[i] or langs[best] == langid.UNKNOWN or post[best] < langid.MIN_POSTERIOR))
    return out


def test_fused_posterior_equals_plain_sums(spark, smoke_dir):
    docs = table(spark, smoke_dir, "documents")
    model = langid.fit_text_model(spark, docs, 30)
    pages = langid.evidence_of_pages(table(spark, smoke_dir, "pages")).withColumn("doc_id", F.lit(None).cast("bigint"))
    extra = spark.createDataFrame([(None, "https://a.b.fr/x", "<html lang='fr'></html>"), (900, None, "<p>la vie"), (901, "https://a.b.fr/x", None)], "page_id bigint, url string, html string")
    more = langid.evidence_of_pages(extra).withColumn("doc_id", F.lit(None).cast("bigint"))
    every = langid.evidence_of_documents(docs).withColumn("page_id", F.lit(None).cast("bigint")).unionByName(pages).unionByName(more)
    every = written(every.withColumn("n", F.monotonically_increasing_id()), "evidence")
    rows = every.withColumn("letters", langid.letters_of(F.col("text"))).orderBy("n").collect()
    got = langid.classify(every, model).orderBy("n").collect()
    for r, (language, posterior, rejected) in zip(got, fused_brute(rows, model, [r.letters for r in rows]), strict=True):
        assert (r.language, r.rejected) == (language, rejected) and abs(r.posterior - posterior) < 1e-4


def test_evidence_moves_short_texts(spark, small_dir, docs):
    model = langid.fit_text_model(spark, docs, 100)
    pages = [(i, f"https://a{i % 3}.host{'x' if i % 2 else 'y'}.{'fr' if i % 2 else 'de'}/p", f"<html lang='{'fr' if i % 2 else 'de'}'><body>{docs_text}</body></html>") for i, docs_text in enumerate(_some_texts(docs))]
    pages.append((900, "https://a1.hostx.fr/q", "<html lang='fr'><body>on</body></html>"))
    pages.append((901, None, None))
    rows = langid.evidence_of_pages(spark.createDataFrame(pages, "page_id bigint, url string, html string"))
    got = {r.page_id: r for r in langid.classify(rows, model).collect()}
    assert len(got) == len(pages) and got[901].rejected
    assert got[900].language == "fr" and not got[900].rejected  # two letters, but the address and the markup speak
    assert np.mean([got[i].language == ("fr" if i % 2 else "de") for i in range(40)]) > 0.97


def _some_texts(docs) -> list[str]:
    by = {x: [r.text for r in docs.where((F.col("lang") == x) & (F.col("n_chars") > 300)).orderBy("doc_id").limit(20).collect()] for x in ("de", "fr")}
    return [by["fr" if i % 2 else "de"][i // 2] for i in range(40)]


def test_language_awkward(spark, awkward):
    got = langid.stage_language(spark, awkward, "")
    assert got.columns == awkward.columns and {r.doc_id for r in got.collect()} >= {1, 2, 7, 12}
    assert not {r.doc_id for r in got.collect()} & {3, 4, 5, 6, 9, 10}
    assert langid.stage_language(spark, empty(spark), "").count() == 0


# mixing


def test_pivotal_is_unbiased_and_keeps_sums():
    rng = np.random.default_rng(3)
    p = np.array([0.2, 0.7, 0.5, 0.9, 0.1, 0.6, 0.0, 1.0])
    total = np.zeros(len(p))
    for _ in range(4000):
        values, open_ = mixing.pivotal(p, rng.random(len(p)))
        assert abs(values.sum() - p.sum()) < 1e-9 and open_ < 0  # the sum is whole
        total += values
    assert np.abs(total / 4000 - p).max() < 0.04


@pytest.mark.parametrize("leaf_rows", [10_000, 40])
def test_mix_meets_targets(spark, docs, leaf_rows):
    weights = {"src0": 5.0, "src1": 1.0, "src2": 0.3}
    got = mixing.mix(docs, weights, total=1234, leaf_rows=leaf_rows, fan_in=3).toPandas()
    assert len(got) == 1000 and got["doc_id"].is_unique
    for source, part in got.groupby("source"):
        target = 1234 * weights.get(source, 0) / 6.3
        assert abs(part["copies"].sum() - target) < 1
        assert part["copies"].between(np.floor(part["expected"] - 1e-9), np.ceil(part["expected"] + 1e-9)).all()
    again = mixing.mix(docs.repartition(7), weights, total=1234, leaf_rows=leaf_rows, fan_in=3).toPandas()
    assert got.sort_values("doc_id")["copies"].tolist() == again.sort_values("doc_id")["copies"].tolist()


def test_mix_equals_a_plain_tree(spark, docs):
    """The same leaves, uniforms and levels, one row after the other in plain Python."""
    seed, leaf_rows, fan_in = mixing.SEED, 60, 3
    n = docs.count()
    leaves = -(-n // leaf_rows)
    levels = []
    k = leaves
    while k > 1:
        k = -(-k // fan_in)
        levels.append(k)
    uniform = lambda *x: (F.xxhash64("doc_id", *[F.lit(v) for v in x]).bitwiseAND(F.lit((1 << 53) - 1))) / float(1 << 53)
    cols = [F.pmod(F.xxhash64("doc_id", F.lit(seed + 1)), F.lit(leaves)).alias("leaf"), uniform(seed).alias("u0"), uniform(seed + 3).alias("last"), *[uniform(seed + 2, k).alias(f"u{i + 1}") for i, k in enumerate(levels)]]
    rows = {r.doc_id: r for r in docs.select("doc_id", "source", *cols).collect()}
    got = {r.doc_id: r for r in mixing.mix(docs, total=777, leaf_rows=leaf_rows, fan_in=fan_in).collect()}
    p = {i: r.expected - np.floor(r.expected) for i, r in got.items()}
    open_, leaf = set(rows), {i: r.leaf for i, r in rows.items()}
    value = dict(p)
    for level in range(len(levels) + 1):
        if level:
            leaf = {i: leaf[i] // fan_in for i in open_}
        groups = defaultdict(list)
        for i in open_:
            groups[leaf[i], rows[i].source].append(i)
        open_ = set()
        for members in groups.values():
            members.sort(key=lambda i: (rows[i][f"u{level}"], i))
            carry = None
            for i in members:
                if value[i] <= mixing.EPS or value[i] >= 1 - mixing.EPS:
                    value[i] = round(value[i])
                elif carry is None:
                    carry = i
                else:
                    a, b, u = value[carry], value[i], rows[i][f"u{level}"]
                    if a + b < 1:
                        first = u * (a + b) < a
                        value[carry], value[i] = (a + b, 0.0) if first else (0.0, a + b)
                        carry = carry if first else i
                    else:
                        first = u * (2 - a - b) < 1 - b
                        value[carry], value[i] = (1.0, a + b - 1) if first else (a + b - 1, 1.0)
                        carry = i if first else carry
                    if value[carry] <= mixing.EPS or value[carry] >= 1 - mixing.EPS:
                        value[carry], carry = round(value[carry]), None
            if carry is not None:
                open_.add(carry)
    for i in open_:
        value[i] = 1 if rows[i].last < value[i] else 0
    assert {i: int(np.floor(r.expected)) + int(round(value[i])) for i, r in got.items()} == {i: r.copies for i, r in got.items()}


def test_mix_awkward(spark, awkward):
    got = mixing.stage_mix(spark, awkward, "")
    assert got.columns == awkward.columns and got.where("doc_id is null").count() == 1
    copies = {(r.doc_id, r.source): r.copies for r in mixing.mix(awkward).collect()}
    assert Counter((r.doc_id, r.source) for r in got.where("doc_id is not null").collect()) == +Counter({k: v * (2 if k[0] == 2 else 1) for k, v in copies.items()})
    assert mixing.stage_mix(spark, empty(spark), "").count() == 0


# packing


def test_packing_places_every_word_once(docs):
    got = packing.pack(docs, 256, rounds=60).toPandas()
    assert got.groupby("bin_id")["length"].sum().max() <= 256
    assert sorted(got["bin_id"].unique()) == list(range(got["bin_id"].nunique())) and not got.duplicated(["bin_id", "slot"]).any()
    for r in docs.select("doc_id", packing.length_of(F.col("text")).alias("n")).collect()[:200]:
        mine = got[got["doc_id"] == r.doc_id].sort_values("start")
        assert mine["length"].sum() == r.n and (mine["start"].to_numpy() == np.r_[0, mine["length"].cumsum()[:-1]]).all()
    assert got["bin_id"].nunique() <= 1.02 * got["length"].sum() / 256 + 2


def test_solver_near_its_bound_and_exact_on_small_cases():
    for seed in range(8):
        r = random.Random(seed)
        histogram = dict(Counter(r.randint(3, 60) for _ in range(300)))
        plan, bound = packing.solve(histogram, 60, 200)
        held: Counter = Counter()
        for config, times in plan:
            assert sum(x * k for x, k in config.items()) <= 60 and times > 0
            held.update({x: k * times for x, k in config.items()})
        assert held == Counter(histogram)
        bins = sum(t for _, t in plan)
        assert bound - 1e-6 <= bins <= 1.06 * bound + 2
    assert sum(t for _, t in packing.solve({6: 10, 4: 10}, 10, 50)[0]) == 10
    assert sum(t for _, t in packing.solve({5: 4, 3: 4, 2: 4}, 10, 50)[0]) == 4


def test_program_beats_best_fit_on_triplets():
    for seed in range(3):
        r = random.Random(seed)
        histogram: Counter = Counter()
        for _ in range(25):
            a, b = r.randint(250, 370), r.randint(250, 370)
            for x in (a, b, 1000 - a - b):
                histogram[x] += 60
        plan, bound = packing.solve(dict(histogram), 1000, 300)
        lengths = np.array(sorted(histogram))
        plain = packing.best_fit_decreasing(lengths, np.array([histogram[int(x)] for x in lengths]), 1000)
        assert bound - 1e-6 <= sum(t for _, t in plan) < sum(t for _, t in plain)


def test_knapsack_equals_enumeration():
    rng = np.random.default_rng(1)
    for _ in range(20):
        lengths = np.unique(rng.integers(1, 15, 5))
        values = rng.random(len(lengths))
        chosen, worth = packing.best_configuration(lengths, values, np.full(len(lengths), 99), 17)
        best = np.zeros(18)
        for c in range(1, 18):
            best[c] = max([best[c - 1], *(values[i] + best[c - n] for i, n in enumerate(lengths) if n <= c)])
        assert abs(worth - best[17]) < 1e-9 and sum(lengths[i] * k for i, k in chosen.items()) <= 17
        assert abs(sum(values[i] * k for i, k in chosen.items()) - best[17]) < 1e-9


def test_the_program_places_nearly_all(spark):
    docs = table(spark, "/root/testdata/sf0.1", "documents")
    lengths = Counter()
    for r in docs.select(packing.length_of(F.col("text")).alias("n")).collect():
        lengths.update([packing.CAPACITY] * ((r.n - 1) // packing.CAPACITY) + [(r.n - 1) % packing.CAPACITY + 1])
    report: dict = {}
    plan, bound = packing.solve(dict(lengths), packing.CAPACITY, report=report)
    assert sum(t for _, t in plan) <= 1.01 * bound + 1 and report["by_program"] > 0.5


def test_lengths_may_be_tokens(docs, ranks):
    counted = docs.join(token_counts.token_counts(docs, ranks), "doc_id")
    got = packing.pack(counted, 512, rounds=40, length=F.col("n_tokens") + 1).toPandas()
    want = {r.doc_id: r.n_tokens + 1 for r in counted.collect()}
    assert got.groupby("doc_id")["length"].sum().to_dict() == want and got.groupby("bin_id")["length"].sum().max() <= 512


def test_packing_awkward(spark, awkward):
    got = packing.pack(awkward).toPandas()
    assert got.groupby("bin_id")["length"].sum().max() <= packing.CAPACITY
    assert got["length"].sum() == awkward.agg(F.sum(packing.length_of(F.col("text")))).first()[0]
    assert packing.pack(empty(spark)).count() == 0


# tokens


@pytest.fixture(scope="module")
def ranks():
    return tokens.load_ranks()


def test_chunks_encode_as_whole_texts(ranks):
    encode = tokens.chunk_encoder(ranks)
    for t in ["", " ", "a b", " a  b ", "a\n b", "a \nb", "x\n\n y \t z", "don't we'll", "été 12½ ²³", "a b ", "日本 語", "a  b", "\n a", "tab\t b", *("".join(random.Random(i).choice("ab \n\t.'1é") for _ in range(30)) for i in range(400))]:
        assert np.frombuffer(encode.ids(t), encode.dtype).tolist() == encode.encode(t), repr(t)


def test_store_round_trip(spark, docs, ranks, tmp_path):
    ids = token_store.encode_ids(docs, ranks)
    dictionary = token_store.train_dictionary(ids)
    encoded = token_store.encode_corpus(ids, dictionary)
    folder = f"file://{tmp_path}/store"
    token_store.write_store(encoded, dictionary, folder)
    encode = tokens.encoder(ranks).encode_ordinary
    texts = {r.doc_id: r.text for r in docs.collect()}
    index = spark.read.parquet(f"{folder}/index").collect()
    assert len(index) == len(texts)
    for row in index[::23]:
        ids = token_store.read_document(folder, row)
        assert ids.tolist() == encode(texts[row.doc_id]) and len(ids) == row.n_tokens


def test_dictionary_helps_short_documents_at_every_depth(docs, ranks, monkeypatch):
    ids = token_store.encode_ids(docs, ranks)
    short = ids.where("length(raw) < 200")
    size = lambda d: token_store.encode_corpus(short, d).agg(F.sum("n_bytes")).first()[0]
    assert size(token_store.train_dictionary(ids)) < 0.9 * size(b"")
    monkeypatch.setattr(token_store, "LAST_BYTES", 200_000)  # several levels of chunks
    monkeypatch.setattr(token_store, "CHUNK_BYTES", 300_000)
    assert size(token_store.train_dictionary(ids)) < 0.93 * size(b"")


def test_store_awkward(spark, awkward, ranks):
    ids = token_store.encode_ids(awkward, ranks)
    dictionary = token_store.train_dictionary(ids)
    got = token_store.encode_corpus(ids, dictionary).collect()
    assert len(got) == 15
    by = {r.doc_id: r for r in got}
    assert by[3].frame is None and by[5].n_tokens == 0 and len(token_store.decode(by[5].frame, dictionary)) == 0
    none = token_store.encode_ids(empty(spark), ranks)
    assert token_store.train_dictionary(none) == b"" and token_store.encode_corpus(none, b"").count() == 0


@pytest.mark.parametrize("frequent", [1 << 18, 500, 0])
def test_counts_equal_encoding(docs, ranks, frequent):
    encode = tokens.encoder(ranks).encode_ordinary
    part = docs.where("doc_id % 4 = 0")
    want = {r.doc_id: len(encode(r.text)) for r in part.collect()}
    got = token_counts.token_counts(part, ranks, frequent).collect()
    assert {r.doc_id: r.n_tokens for r in got} == want and len(got) == len(want)


def test_counts_awkward(spark, awkward, ranks):
    encode = tokens.encoder(ranks).encode_ordinary
    want = Counter((r[0], len(encode(r[1] or ""))) for r in awkward_rows())
    assert Counter((r.doc_id, r.n_tokens) for r in token_counts.token_counts(awkward, ranks, 10).collect()) == want
    assert token_counts.token_counts(empty(spark), ranks).count() == 0


# neighbours


def test_neighbours_recall_and_distances(spark, small_dir):
    rows = table(spark, small_dir, "embeddings")
    x = rows.orderBy("vec_id").toPandas()
    m, ids = np.stack(x["embedding"]).astype(float), x["vec_id"].to_numpy()
    vectors = written(ann.clean_vectors(rows), "v")
    books = ann.learn(vectors, 8, 64, 2)
    for block, rerank in ((16_384, 120), (150, 40)):
        got = ann.search(vectors, books, 10, rerank, block).toPandas()
        assert len(got) == 10 * len(ids) and (got["vec_id"] != got["neighbour_id"]).all()
        hits = 0
        for i, part in got.groupby("vec_id"):
            d = ((m - m[ids == i][0]) ** 2).sum(1)
            d[ids == i] = np.inf
            hits += len(set(ids[np.argsort(d)[:10]]) & set(part["neighbour_id"]))
            assert np.allclose(np.sqrt([d[ids == j][0] for j in part.sort_values("rank")["neighbour_id"]]), part.sort_values("rank")["distance"], atol=1e-4)
        assert hits / len(got) >= 0.9


def test_neighbours_query_set(spark, small_dir):
    """The ids divisible by 50, all of them, each against all vectors."""
    x = table(spark, small_dir, "embeddings").orderBy("vec_id").toPandas()
    m, ids = np.stack(x["embedding"]).astype(float), x["vec_id"].to_numpy()
    got = ann.op3_neighbours(spark, small_dir).toPandas()
    assert set(got["vec_id"]) == set(ids[ids % 50 == 0]) and len(got) == 10 * (ids % 50 == 0).sum()
    hits = 0
    for i, part in got.groupby("vec_id"):
        d = ((m - m[ids == i][0]) ** 2).sum(1)
        d[ids == i] = np.inf
        hits += len(set(ids[np.argsort(d)[:10]]) & set(part["neighbour_id"]))
    assert hits / len(got) >= 0.9


def test_neighbours_recall_of_many_blocks(spark):
    """20,000 directions without clusters, in several blocks; more vectors than the codebooks are fitted to."""
    n = 20_000
    m = np.random.default_rng(3).normal(size=(n, 64)).astype(np.float32)
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    vectors = written(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(m)], "vec_id bigint, x array<float>"), "v")
    asked = vectors.where("vec_id % 200 = 0")
    books = ann.learn(vectors, rows=8_000)
    for block in (16_384, 6_000):
        got = ann.search(vectors, books, block=block, queries=asked).toPandas()
        assert len(got) == 10 * (n // 200) and set(got["vec_id"]) == set(range(0, n, 200))
        hits = 0
        for i, part in got.groupby("vec_id"):
            d = ((m - m[i]) ** 2).sum(1)
            d[i] = np.inf
            hits += len(set(np.argpartition(d, 10)[:10]) & set(part["neighbour_id"]))
        assert hits / len(got) >= 0.9


def test_best_of_holds_the_greatest():
    scores = np.random.default_rng(1).normal(size=(20, 3_000)).astype(np.float32)
    scores[0] = 0  # ties
    scores[1, ::16] = 9  # the sample misleads
    for most in (1, 11, 200, 2_999, 3_000, 5_000):
        for row, found in zip(scores, ann.best_of(scores, most), strict=True):
            want = min(most, 3_000)
            assert len(found) >= want == len(np.unique(found)[:want]) and np.sort(row[found])[-want] == np.sort(row)[-want]


def test_near_enough_keeps_ties_and_great_values():
    x = np.repeat(np.random.default_rng(2).normal(size=(40, 8)).astype(np.float32), 30, axis=0)  # copies, more than are asked for
    for scale in (np.float32(1), np.float32(1e-12), np.float32(1e30)):
        with np.errstate(over="ignore", invalid="ignore"):
            y = x * scale
            kept = ann.near_enough(y, np.arange(len(y)), y[100] * np.float32(1.01), (y**2).sum(1), 10)
        exact = ((y.astype(np.float64) - y[100].astype(np.float64) * np.float32(1.01)) ** 2).sum(1)
        assert set(np.flatnonzero(exact <= np.sort(exact)[9])) <= set(kept)


def test_lookups_equal_products_with_reconstructions():
    rng = np.random.default_rng(6)
    books, q = rng.normal(size=(5, 32, 16)).astype(np.float32), rng.normal(size=(7, 16)).astype(np.float32)
    codes = rng.integers(0, 32, (5, 2_500)).astype(np.uint8)
    near = sum(books[m][codes[m]] for m in range(5))
    half = (near**2).sum(1) / 2
    assert np.allclose(ann.lookup_scores(np.einsum("qd,mkd->mkq", q, books), codes, half), q @ near.T - half, atol=1e-3)


def test_beam_beats_greedy_and_norms_are_of_reconstructions():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 16)).astype(np.float32)
    books = rng.normal(size=(4, 32, 16)).astype(np.float32) / 2
    errors = []
    for beam in (1, 8):
        codes, near = ann.beam_encode(x, books, beam)
        assert np.allclose(near, sum(books[m][codes[:, m]] for m in range(4)), atol=1e-4)
        errors.append(((x - near) ** 2).sum())
    assert errors[1] < errors[0]


def test_neighbours_awkward(spark):
    rows = [(1, [0.0, 1.0]), (2, [0.0, 1.0]), (2, [0.0, 1.0]), (3, None), (4, [1.0]), (5, [1.0, None]), (6, [float("nan"), 1.0]), (None, [1.0, 1.0]), (7, [3.0, 3.0]), (8, []), (9, [float("inf"), 1.0]), (10, [0.0, float("-inf")])]
    vectors = ann.clean_vectors(spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").withColumn("rank", F.lit(1)).withColumn("part", F.lit(1)))
    got = ann.search(vectors, ann.learn(vectors, 2, 4, 1)).collect()
    assert {(r.vec_id, r.neighbour_id, r["rank"]) for r in got} == {(1, 2, 1), (1, 7, 2), (2, 1, 1), (2, 7, 2), (7, 1, 1), (7, 2, 2)}
    none = ann.clean_vectors(spark.createDataFrame([], "vec_id bigint, embedding array<float>"))
    assert ann.search(none, ann.learn(none)).count() == 0


# passages


def passages_brute(texts: dict, t: int) -> dict:
    """Windows by content, then runs of windows that another document has."""
    where = defaultdict(set)
    for i, x in texts.items():
        w = x.split()
        for s in range(len(w) - t + 1):
            where[tuple(w[s : s + t])].add(i)
    out = defaultdict(set)
    for i, x in texts.items():
        w = x.split()
        hit = [s for s in range(len(w) - t + 1) if len(where[tuple(w[s : s + t])]) > 1]
        start = None
        for j, s in enumerate(hit):
            start = s if start is None else start
            if j + 1 == len(hit) or hit[j + 1] != s + 1:
                out[i].add((start, s + t - start))
                start = None
    return dict(out)


def test_passages_equal_brute_force(docs):
    part = docs.where("doc_id < 400")
    texts = {r.doc_id: r.text for r in part.collect()}
    for t, seed in ((50, 20), (12, 5)):
        got = defaultdict(set)
        for r in substrings.repeated_passages(part, t, seed).collect():
            got[r.doc_id].add((r.start_word, r.n_words))
            assert r.partners and r.doc_id not in r.partners
        assert dict(got) == passages_brute(texts, t)


def test_planted_passages(spark):
    shared = prose(55, 999)
    rows = [(i, prose(80, i) + " " + shared + " " + prose(40, 500 + i), "en", "a", 1) for i in range(200)] + [(900 + i, prose(200, 3000 + i), "en", "a", 1) for i in range(50)]
    got = substrings.repeated_passages(spark.createDataFrame(rows, DOCS)).collect()
    assert {r.doc_id for r in got} == set(range(200)) and all(r.start_word <= 80 and 135 <= r.start_word + r.n_words < 150 for r in got)


def test_passages_awkward(spark, awkward):
    got = {(r.doc_id, r.start_word, r.n_words) for r in substrings.repeated_passages(awkward).collect()}
    assert got == {(1, 0, 120), (2, 0, 120), (12, 0, 120), (7, 0, 60_000), (8, 0, 60_000)}
    assert substrings.repeated_passages(empty(spark)).count() == 0


def pairs_brute(texts: dict, t: int) -> set:
    """Maximal common spans of at least ``t`` words of every two documents, pair by pair."""
    words = {i: x.split() for i, x in texts.items()}
    at = {i: defaultdict(list) for i in words}
    for i, w in words.items():
        for s in range(len(w) - t + 1):
            at[i][tuple(w[s : s + t])].append(s)
    out = set()
    for a in words:
        for b in words:
            if a < b:
                hits = {(x, y) for k in at[a].keys() & at[b].keys() for x in at[a][k] for y in at[b][k]}
                for x, y in hits:
                    if (x - 1, y - 1) not in hits:
                        n = 0
                        while (x + n, y + n) in hits:
                            n += 1
                        out.add((a, x, b, y, n + t - 1))
    return out


def pairs_found(shared, t: int) -> set:
    got = [(r.a, r.a_start, r.b, r.b_start, r.n_words) if r.a < r.b else (r.b, r.b_start, r.a, r.a_start, r.n_words) for r in substrings.passage_pairs(shared, t).collect()]
    assert len(got) == len(set(got))
    return set(got)


def test_passage_pairs_equal_pairwise_brute_force(spark, docs):
    hot, x, y = prose(70, 1), prose(90, 2), prose(55, 3)
    made = {
        0: f"{x} {prose(30, 4)}", 1: f"{prose(9, 5)} {' '.join(x.split()[:60])} {prose(20, 6)}", 2: f"{prose(12, 7)} {' '.join(x.split()[11:71])}", 3: f"{' '.join(x.split()[5:])} {y}",
        4: f"{y} {prose(60, 8)} {y}", **{10 + i: f"{prose(i, 9 + i)} {' '.join(hot.split()[i % 5 : 70 - i % 7])} {prose(8, 40 + i)}" for i in range(12)},
    }
    part = docs.where("doc_id < 150")
    for rows, sizes in ((made, ((50, 20), (12, 5))), ({r.doc_id: r.text for r in part.collect()}, ((50, 20),))):
        df = spark.createDataFrame([(i, v) for i, v in rows.items()] + [next(iter(rows.items()))], "doc_id bigint, text string")
        for t, seed in sizes:
            shared = written(substrings.shared_passages(df, t, seed), "shared")
            want = pairs_brute(rows, t)
            assert want and pairs_found(shared, t) == want
            for r in shared.groupBy("passage").agg(F.count_distinct("row").alias("n"), F.min("n_docs").alias("a"), F.max("n_docs").alias("b"), F.count_distinct("n_words").alias("k")).collect():
                assert r.n == r.a == r.b > 1 and r.k == 1
            if rows is made:
                partners = defaultdict(set)
                for a, _, b, _, _ in want:
                    partners[a].add(b)
                    partners[b].add(a)
                got = defaultdict(set)
                for r in substrings.repeated_passages(df, t, seed).collect():
                    got[r.doc_id] |= set(r.partners)
                assert got == partners


def test_runs_of_different_partners_stay_apart(spark):
    x = prose(71, 77).split()
    rows = [(1, " ".join(x)), (2, " ".join(x[:60])), (3, " ".join(x[11:]))]
    got = substrings.shared_passages(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert sorted((r.doc_id, r.start_word, r.n_words) for r in got) == [(1, 0, 60), (1, 11, 60), (2, 0, 60), (3, 0, 60)]


# toxicity


def chain_brute(emission, transition, start):
    import itertools

    n, z, p = len(emission), 0.0, np.zeros(len(emission))
    for y in itertools.product((0, 1), repeat=n):
        s = start[y[0]] + sum(e * v for e, v in zip(emission, y)) + sum(transition[a, b] for a, b in zip(y, y[1:]))
        z += np.exp(s)
        p += np.exp(s) * np.array(y)
    return p / z, np.log(z)


def test_marginals_equal_enumeration(monkeypatch):
    monkeypatch.setattr(toxicity, "LANE", 4)
    rng = np.random.default_rng(2)
    lengths = np.array([3, 0, 1, 9, 4, 10])
    e, t, s = rng.normal(size=lengths.sum()) * 2, rng.normal(size=(2, 2)), rng.normal(size=2)
    p, logs, pair = toxicity.marginals(e, lengths, t, s)
    at = 0
    for n, z in zip(lengths, logs):
        if n:
            want, lz = chain_brute(e[at : at + n], t, s)
            assert np.allclose(p[at : at + n], want) and abs(lz - z) < 1e-9
        at += n
    assert abs(pair.sum() - sum(max(0, n - 1) for n in lengths)) < 1e-6


def test_toxic_documents_held_out(spark):
    labels = table(spark, "/root/testdata/sf0.1", "labels")
    docs = table(spark, "/root/testdata/sf0.1", "documents").join(F.broadcast(labels.select("doc_id")), "doc_id", "left_semi")
    fold = F.pmod(F.xxhash64("doc_id"), F.lit(3))
    field = toxicity.fit(*toxicity.sample(docs, labels.where(fold > 0)), epochs=40)
    got = toxicity.tag(docs, field).join(labels.where(fold == 0), "doc_id").collect()
    rate = lambda value: np.mean([r[3] for r in got if r[-1] == value])
    assert rate(1) > 0.88 and rate(0) < 0.01


def test_spans_are_offsets(spark):
    bad = [f"{prose(4, i)} {'idiot' if i % 2 else 'clown'} {prose(4, 700 + i)}" for i in range(60)]
    field = toxicity.fit(bad, [prose(12, 5000 + i) for i in range(200)])
    text = f"{prose(3, 1)} a Clown, {prose(3, 9)} IDIOT"
    docs = spark.createDataFrame([(1, text), (2, "nothing"), (3, None), (4, ""), (None, "an idiot"), (2, "nothing")], "doc_id bigint, text string")
    got = toxicity.tag(docs, field).collect()
    assert [[text[s.start : s.end].lower() for s in r.spans] for r in got[:1]] == [["clown", "idiot"]]
    assert [[(s.start, s.end) for s in r.spans] for r in got[1:]] == [[], [], [], [(3, 8)], []] and [r.toxic for r in got] == [True, False, False, False, True, False]


def test_every_document_is_scored(spark, smoke_dir):
    got = toxicity.op7_toxic_spans(spark, smoke_dir).collect()
    assert Counter(r.doc_id for r in got) == Counter(r.doc_id for r in table(spark, smoke_dir, "documents").select("doc_id").collect())
    assert {r.toxic for r in got} == {True, False} and all((r.peak >= toxicity.THRESHOLD) == bool(r.spans) for r in got)


def test_offsets_are_of_the_text_as_given(spark):
    """Lower-casing changes the length of some letters; offsets must not."""
    bad = [f"{prose(4, i)} {'idiot' if i % 2 else 'clown'} {prose(4, 700 + i)}" for i in range(60)]
    field = toxicity.fit(bad, [prose(12, 5000 + i) for i in range(200)])
    texts = ["İdiot clown", "İİİ ßtraße CLOWN é idiot", "日本 Clown語 clown"]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for r in toxicity.tag(rows, field).collect():
        found = [texts[r.doc_id][s.start : s.end].lower() for s in r.spans]
        assert "clown" in " ".join(found).split() and all(x == x.strip() for x in found)


def test_forms_outside_the_derived_list_are_tagged(spark):
    """Stems carry over: inflections that were never seen are tagged, unrelated words are not."""
    bad = [f"{prose(4, i)} {('idiotic', 'idiots', 'clownish', 'clowns')[i % 4]} {prose(4, 700 + i)}" for i in range(120)]
    field = toxicity.fit(bad, [prose(12, 5000 + i) for i in range(300)])
    got = toxicity.tag(spark.createDataFrame([(1, f"{prose(3, 1)} idiotically {prose(3, 2)} clowning"), (2, prose(30, 9))], "doc_id bigint, text string"), field).collect()
    assert len(got[0].spans) == 2 and got[1].spans == []


def test_toxicity_awkward(spark, awkward):
    field = toxicity.fit([], [])
    assert toxicity.tag(awkward, field).where("not toxic").count() == 15
    assert toxicity.tag(empty(spark), field).count() == 0
    labels = spark.createDataFrame([(1, 0, 0), (None, 1, 1), (5, None, None), (3, 1, 1)], "doc_id bigint, quality int, toxic int")
    toxic, clean = toxicity.sample(awkward, labels)
    assert toxic == [] and len(clean) == 1


def test_written_tables_can_be_cleared(spark, monkeypatch):
    from pathlib import Path

    from unioncount.llm import common

    monkeypatch.setattr(common, "_WRITTEN", [])
    written(spark.range(3), "brief")
    path = Path(common._WRITTEN[0].removeprefix("file://"))
    assert path.is_dir()
    common.clear_written(spark)
    assert not path.exists() and common._WRITTEN == []


# pipeline


def test_pipeline_equals_brute_force_stage_by_stage(spark, smoke_dir):
    import corpus_pipeline

    docs = table(spark, smoke_dir, "documents")
    steps = dict(corpus_pipeline.STAGES)
    rows = lambda df: Counter((r.doc_id, r.text, r.source) for r in df.collect())
    after = written(steps["language_id"](spark, docs, smoke_dir), "a")
    verdict = {(r.doc_id, r.n): r.rejected for r in langid.classify(langid.evidence_of_documents(docs).withColumn("n", F.xxhash64("text")), langid.fit_text_model(spark, docs)).collect()}
    assert rows(after) == Counter((r.doc_id, r.text, r.source) for r in docs.withColumn("n", F.xxhash64("text")).collect() if not verdict[r.doc_id, r.n])
    least: dict = {}
    for r in after.collect():
        least[r.text] = min(least.get(r.text, r.doc_id), r.doc_id)
    exact = written(steps["exact_dedup"](spark, after, smoke_dir), "b")
    assert {(r.text, r.doc_id) for r in exact.collect()} == set(least.items()) and exact.count() == len(least)
    near = written(steps["near_dedup"](spark, exact, smoke_dir), "c")
    fps = simhash.fingerprints(exact).toPandas().sort_values("doc_id").reset_index(drop=True)
    pairs = near_brute(fps[["f0", "f1", "f2", "f3"]].to_numpy().view(np.uint64), simhash.RADIUS)
    label = list(range(len(fps)))
    for _ in range(20):
        for a, b in pairs:
            label[a] = label[b] = min(label[a], label[b])
    dropped = {int(fps["doc_id"][i]) for i, x in enumerate(label) if x != i}
    kept = {r.doc_id for r in near.collect()}
    lost = {r.doc_id for r in exact.collect()} - kept
    assert lost <= dropped and len(lost) >= 0.9 * len(dropped)
    mixed = written(steps["mix_sources"](spark, near, smoke_dir), "d")
    copies = {(r.doc_id, r.source): r.copies for r in mixing.mix(near).collect()}
    assert Counter((r.doc_id, r.source) for r in mixed.collect()) == Counter({k: v for k, v in copies.items() if v})
    packed = steps["pack_sequences"](spark, mixed, smoke_dir).toPandas()
    words = Counter()
    for r in mixed.collect():
        words[r.doc_id] += len(r.text.split()) + 1
    assert packed.groupby("doc_id")["length"].sum().to_dict() == dict(words) and packed.groupby("bin_id")["length"].sum().max() <= packing.CAPACITY


def test_text_ids_count_as_null(spark, ranks):
    df = spark.createDataFrame([("a1", "one two", "en", "s", 1), ("2", "three four", "en", "s", 1)], "doc_id string, text string, lang string, source string, n_chars bigint")
    assert Counter(r.doc_id for r in token_counts.token_counts(df, ranks).collect()) == Counter([None, 2])
    assert [r.doc_id for r in mixing.mix(df).collect()] == [2] and substrings.shared_passages(df, 2, 1).count() == 0
    assert {r.doc_id for r in toxicity.tag(df, toxicity.fit([], [])).collect()} == {None, 2}
    assert {r.doc_id for r in token_store.encode_ids(df, ranks).collect()} == {None, 2}


def test_pipeline_stages(spark, smoke_dir, awkward):
    import corpus_pipeline

    columns = table(spark, smoke_dir, "documents").columns
    docs = table(spark, smoke_dir, "documents")
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        docs = written(stage(spark, docs, smoke_dir), name)
        if i < len(corpus_pipeline.STAGES) - 1:
            assert docs.columns == columns and docs.count() > 100
    assert docs.groupBy("bin_id").agg(F.sum("length").alias("n")).agg(F.max("n")).first()[0] <= packing.CAPACITY
    for docs in (awkward, empty(spark)):
        for name, stage in corpus_pipeline.STAGES:
            docs = written(stage(spark, docs, smoke_dir), name)
