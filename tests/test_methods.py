"""Worked examples, laws, closed forms and edge cases of the methods."""

from __future__ import annotations

import math
import random
import statistics

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from pyspark.sql import types as T

from unioncount import audit, baselines, experiments, field, hashing, measures, noise, privacy, protocol, shares, sketches, sources, theory
from unioncount.estimate import alpha, mr_estimate, mr_mean_estimate, zc_estimate
from unioncount.params import ORACLE, P61, P72, ProtocolConfig, SketchParams, choose_width, fresh_seed
from unioncount.shares import Keys, Shared
from unioncount.zerotest import deal_tests, opened_column, run_tests, zero_test

PAIRS = "holder string, element string"


def rows(spark, n, d=3):
    return spark.createDataFrame([(str(i % d), str(i)) for i in range(n)], PAIRS)


def values(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_rank_examples(spark):
    strings = {"1011": 0, "1010": 1, "1100": 2, "1000": 3, "0000": 4}
    got = spark.createDataFrame([(x, int(x, 2)) for x in strings], "s string, v bigint").select("s", hashing.rank_of(F.col("v"), 5).alias("r")).collect()
    assert {r.s: r.r for r in got} == strings


def test_merge_laws(spark):
    p = SketchParams(16, 10)
    a, b = rows(spark, 200, 4), rows(spark, 300, 7)
    one = sketches.zc_sketch(a.union(b), p, ())
    assert values(one) == values(sketches.merge(sketches.zc_sketch(a, p).union(sketches.zc_sketch(b, p)))) == values(sketches.merge_tree(sketches.zc_sketch(b, p).union(sketches.zc_sketch(a, p)).union(sketches.zc_sketch(a, p))))
    for build in (lambda x: sketches.fz_sketch(x, p), lambda x: sketches.mr_sketch(x, p, offset=1)):
        assert values(sketches.merge(build(a).union(build(b)))) == values(sketches.merge(build(b.union(a).union(a))))


def test_edges(spark):
    p = SketchParams(16, 10)
    none = spark.createDataFrame([], PAIRS)
    assert sketches.zero_total(sketches.zc_sketch(none, p), p).first().z == 160
    assert sketches.fz_total(sketches.fz_sketch(none, p), p).first().z_star == 0
    assert spark.range(1).select(mr_mean_estimate(F.lit(0), 64).alias("e")).first().e == pytest.approx(0.783 * 64)
    one = spark.createDataFrame([("a", "x")] * 50 + [("b", "x"), ("b", None)], PAIRS)
    assert sketches.zero_total(sketches.merge(sketches.zc_sketch(one, p)), p).first().z == 159
    for m, w in ((16, 2), (16, 3)):
        assert sketches.zero_total(sketches.zc_sketch(rows(spark, 50), SketchParams(m, w), ()), SketchParams(m, w)).first().z >= 0


def test_canonical_text(spark):
    kind = T.StructType([T.StructField("a", T.StringType()), T.StructField("b", T.StringType())])
    df = spark.createDataFrame([(("a", "bc"),), (("ab", "c"),), ((None, "abc"),)], T.StructType([T.StructField("s", kind)]))
    assert len({r[0] for r in df.select(hashing.canon(F.col("s"), kind)).collect()}) == 3
    with pytest.raises(TypeError):
        hashing.canon(F.lit(1), T.MapType(T.StringType(), T.StringType()))


def test_estimator_inverts(spark):
    m, w = 64, 12
    f = lambda n: sum(math.exp(-n * q) for q in theory.rank_probs(m, w)) * m
    grid = [(n, f(n)) for n in (1.0, 50.0, 1000.0, 20000.0)]
    got = spark.createDataFrame(grid, "n double, z double").select("n", zc_estimate(F.col("z"), m, w).alias("e")).collect()
    assert all(r.e == pytest.approx(r.n, rel=1e-6) for r in got)
    ends = spark.createDataFrame([(float(m * w),), (m * w + 40.0,), (-5.0,), (0.0,)], "z double").select(zc_estimate(F.col("z"), m, w).alias("e")).collect()
    assert [r.e for r in ends[:2]] == [0, 0] and all(r.e == pytest.approx(m * 2**w) for r in ends[2:])


def test_moments_match_simulation():
    rng = random.Random(5)
    m, w, n = 8, 6, 40
    zs = []
    for _ in range(3000):
        bits = [0] * m
        for _ in range(n):
            x = 0
            while x < w - 1 and rng.random() < 0.5:
                x += 1
            bits[rng.randrange(m)] |= 1 << x
        zs.append(m * w - sum(b.bit_count() for b in bits))
    assert abs(statistics.fmean(zs) - theory.zc_mean(n, m, w)) < 4 * math.sqrt(theory.zc_var(n, m, w) / 3000)
    assert statistics.variance(zs) == pytest.approx(theory.zc_var(n, m, w), rel=0.1)
    assert theory.zc_var(2000, 64, 12) == pytest.approx(59.72, abs=0.01)
    assert theory.zc_pois_var(300, 64, 12) == pytest.approx(63.4, abs=0.1)


def test_widths_and_bias():
    assert [choose_width("zc", n, 4096) for n in (10**3, 10**5, 10**9)] == [4, 11, 24] and choose_width("fz", 10**9, 1024) == 36
    assert alpha(1024) == pytest.approx(0.7213 / (1 + 1.079 / 1024), rel=1e-3) and alpha(64) == pytest.approx(0.709, abs=1e-3)


def test_privacy_numbers():
    assert privacy.cdp_bound(0.012, 1e-12) == pytest.approx(0.08928, abs=1e-5) and privacy.cdp_to_dp(0.012, 1e-12) == pytest.approx(0.07661, abs=1e-5)
    for eps, bound, inf in ((0.1, 0.01344, 0.01556), (0.3, 0.04025, 0.04544), (0.5, 0.06696, 0.07474)):
        assert privacy.dp_to_cdp(eps, 1e-12) == pytest.approx(bound, abs=1e-5) and privacy.dp_to_cdp(eps, 1e-12, "inf") == pytest.approx(inf, abs=1e-5)
    sigma = 1 / (math.sqrt(20) * 0.012)
    assert sigma == pytest.approx(18.634, abs=1e-3) and privacy.eps_distributed(sigma, 20)[0] == pytest.approx(0.012, abs=1e-6)
    assert privacy.eps_curious(sigma, 20) > 0.012 and privacy.tau(2, 20) < 1e-15
    with pytest.raises(ValueError):
        privacy.eps_distributed(0.4, 5)
    assert privacy.eps_distributed(privacy.calibrate_sigma(0.3, 1e-12, 10, "holder"), 9)[0] <= privacy.dp_to_cdp(0.3, 1e-12) + 1e-9
    ledger = privacy.PrivacyLedger(0.01)
    ledger.charge("a", 0.1)
    with pytest.raises(PermissionError):
        ledger.charge("b", 0.15)


def test_sampler(spark):
    pmf = {r.x: r.pmf for r in noise.pmf_table(spark, 1.5).collect()}
    assert sum(pmf.values()) == pytest.approx(1) and privacy.renyi_divergence(pmf, pmf, 2.0) == pytest.approx(0)
    drawn = noise.draw(spark.range(6000), F.col("id").cast("string"), "t", 1.5).groupBy("noise").count().collect()
    exact = [noise.exact_draw(1.5) for _ in range(6000)]
    for counts in ({r.noise: r["count"] for r in drawn}, {x: exact.count(x) for x in set(exact)}):
        assert sum(counts.values()) == 6000
        chi = sum((counts.get(x, 0) - 6000 * q) ** 2 / (6000 * q) for x, q in pmf.items() if 6000 * q >= 5)
        assert chi < 40


@settings(max_examples=8, deadline=None)
@given(st.lists(st.integers(-(10**15), 10**15), min_size=1, max_size=6), st.integers(2, 5))
def test_sharing_laws(spark, xs, c):
    keys = Keys.agree(c, "h")
    df = spark.createDataFrame([(i, x, 7 * i + 1) for i, x in enumerate(xs)], "cell bigint, x bigint, y bigint")
    share = lambda name: shares.share_input(field.reduce_(F.col(name).cast("decimal(38,0)")), F.col("cell"), keys, "h", name).column()
    df = df.withColumn("sx", share("x")).withColumn("sy", share("y"))
    df = df.withColumn("sum", shares.add_public(shares.add(Shared.of("sx"), shares.scale(Shared.of("sy"), field.constant(3))), field.constant(5), keys).column())
    for r in opened_column(opened_column(df, "sx", "o", keys), "sum", "q", keys).select("x", "y", field.decode_centered(F.col("o")).alias("o"), "o_ok", field.decode_centered(F.col("q")).alias("q"), "q_ok").collect():
        assert (r.o, r.q, r.o_ok, r.q_ok) == (r.x, r.x + 3 * r.y + 5, True, True)


def even(values, cells=8, top=P61) -> float:
    """Distance of values below ``top`` from an even spread."""
    counts = [0] * cells
    for v in values:
        counts[min(cells - 1, int(v) * cells // top)] += 1
    return sum((k - len(values) / cells) ** 2 / (len(values) / cells) for k in counts)


def test_what_is_opened_tells_nothing(spark):
    """Every share of an input, and all four openings of a zero test, spread evenly whatever x is."""
    keys = Keys.agree(3, "u")
    for x in (0, 1):
        df = spark.range(2000).select(F.col("id").alias("cell"), shares.share_input(F.lit(x).cast("decimal(38,0)"), F.col("id"), keys, f"u{x}", "m").column().alias("s"))
        got = run_tests(deal_tests(df, 5, keys, f"u{x}", "t"), "s", "b", 5, keys, f"u{x}", "t").select("s.val", "s.mac", "b_seen").collect()
        for part in [*[[r.val[j] for r in got] for j in range(3)], *[[r.mac[j] for r in got] for j in range(3)], *[[r.b_seen[i] for r in got] for i in range(4)]]:
            assert even(part) < 30


def test_wide_field_equals_whole_numbers(spark):
    rng = random.Random(1)
    pairs = [(rng.randrange(P72), rng.randrange(P72)) for _ in range(60)] + [(P72 - 1, P72 - 1), ((1 << 36) - 1, 1 << 36), (1 << 71, P72 - 2), (0, 5)]
    df = spark.createDataFrame([(str(a), str(b)) for a, b in pairs], "a string, b string").select(F.col("a").cast("decimal(38,0)").alias("a"), F.col("b").cast("decimal(38,0)").alias("b"))
    for r, (a, b) in zip(df.select(field.mul(F.col("a"), F.col("b"), P72).alias("m"), field.add(F.col("a"), F.col("b"), P72).alias("s")).collect(), pairs, strict=True):
        assert (int(r.m), int(r.s)) == (a * b % P72, (a + b) % P72)
    with field.using(P72):
        one = spark.range(1).select(field.mul(field.inverse(field.constant(12345678901234567890)), field.constant(12345678901234567890)).alias("x")).first()
        assert one.x == 1
    with pytest.raises(ValueError), field.using(1 << 90):
        pass


def test_fresh_seeds_differ_and_are_not_shown(spark):
    a, b = ProtocolConfig(seed=fresh_seed()), ProtocolConfig(seed=fresh_seed())
    assert a.seed != b.seed and a.seed not in repr(a)
    keys = protocol.offline_setup(a)
    assert keys.shares != protocol.offline_setup(b).shares and str(keys.shares[0]) not in repr(keys)


def test_batched_check_finds_errors_that_cancel(spark):
    """Two openings altered by opposite amounts: their plain sum would pass, the random combination does not."""
    keys = Keys.agree(3, "b")
    df = spark.range(40).select(F.col("id").alias("cell"), *[shares.share_input(F.col("id").cast("decimal(38,0)"), F.col("id"), keys, "b", t).column().alias(t) for t in ("x", "y")])
    for by, good in ((0, True), (1, False)):
        bad = df.select("cell", shares.tamper(Shared.of("x"), 0, "mac", by).column().alias("x"), shares.tamper(Shared.of("y"), 0, "mac", P61 - by).column().alias("y"))
        ok = shares.cancels(shares.batched([(Shared.of(t), shares.open_(Shared.of(t))) for t in ("x", "y")], F.col("cell"), keys, "b", "check"))
        assert {r[0] for r in bad.select(ok).collect()} == {good}


def test_literal_zero_test_agrees_for_a_prime_near_a_power(spark):
    keys = Keys.agree(2, "l")
    df = spark.range(6).select(F.col("id").alias("cell"), shares.share_input(F.col("id").cast("decimal(38,0)"), F.col("id"), keys, "l", "x").column().alias("s"))
    got = opened_column(zero_test(df, "s", "b", 3, keys, "l", "t", "literal"), "b", "o", keys).select("cell", F.col("o").cast("int").alias("o"), "o_ok", "b_ok").collect()
    assert all(r.o == (r.cell > 0) and r.o_ok and r.b_ok for r in got)
    # the misreading of the literal variant: masks from p up leave the distance of x = 0 above 0
    p, bits = 8111, 13
    assert sum(((a % p) ^ a) != 0 for a in range(1 << bits)) == (1 << bits) - p


def test_lookup_polynomial():
    for k in (1, 2, 5, 9):
        beta = field.lookup_poly(k)
        assert [sum(b * pow(x, t, P61) for t, b in enumerate(beta)) % P61 for x in range(1, k + 2)] == [0] + [1] * k
    assert (P61 - 1) * (P61 - 2) % P61 == 2 and field.wrap_risk(18.6, 20, 4096, 14) < 1e-300


def test_protocol_equals_plain_and_catches_tampering(spark):
    cfg = ProtocolConfig(SketchParams(8, 6), 2, 1.5, "e")
    df = rows(spark, 30, 4)
    secure, plain = protocol.run_puc(df, cfg, 4).first(), protocol.run_plain(df, cfg).first()
    assert (secure.z_noisy, secure.n_hat, secure.mac_ok) == (plain.z_noisy, plain.n_hat, True)
    report = audit.tamper_report(spark.range(20).select(F.col("id").alias("cell"), F.col("id").alias("x")), cfg)
    assert report.where("not detected").count() == 0 and report.count() == 80
    with pytest.raises(ValueError):
        protocol.offline_setup(ProtocolConfig(c=1))


def test_packing(spark):
    p = SketchParams(16, 10)
    sk = sketches.zc_sketch(rows(spark, 100), p)
    packed = sketches.pack(sk, p)
    assert values(sketches.unpack(packed, p)) == values(sk) and "secret" not in repr(SketchParams(16, 10, "secret"))
    with pytest.raises(Exception, match="other parameters"):
        sketches.unpack(packed, SketchParams(16, 10, "other")).collect()


def test_ordering_of_methods(spark):
    """At equal m the zero-count sketch errs least, and by far under noise."""
    states = experiments.states_of(spark, 20_000, ms=(1024, 4096))
    plain = {(r.kind, r.m): r.aare for r in measures.aare(experiments.plain_by_m(states), ["kind", "m"]).collect()}
    assert plain["zc", 1024] < plain["fz", 1024] and plain["zc", 1024] < plain["mr", 1024]
    for mechanism in ("gaussian", "discrete", "distributed"):
        got = {r.kind: r.aare for r in measures.aare(experiments.noisy(states, mechanism, [(0.1, 4096, 20)]), ["kind"]).collect()}
        assert got["zc"] < 0.03 and 4 < got["mr_mean"] / got["zc"] and 100 < got["fz"] / got["zc"]


def test_noise_falls_with_eps_and_m(spark):
    states = experiments.states_of(spark, 20_000, ms=(1024, 4096))
    got = {(r.eps, r.m): r.aare for r in measures.aare(experiments.noisy(states, "distributed", [(0.1, 1024, 20), (0.5, 1024, 20), (0.1, 4096, 20)]).where("kind = 'zc'"), ["eps", "m"]).collect()}
    assert got[0.5, 1024] < got[0.1, 1024] and got[0.1, 4096] < got[0.1, 1024]


def test_scalings_of_noise_by_holders(spark):
    states = experiments.states_of(spark, 1000, ms=(4096,))
    at = lambda k: {r.d: r.aare for r in measures.aare(experiments.noisy(states, "distributed", [(0.1, 4096, h) for h in (5, 25)], k).where("kind = 'zc'"), ["d"]).collect()}
    flat, up, down = at("target_eps"), at("per_holder"), at("over_d")
    assert 0.7 < flat[5] / flat[25] < 1.4 and up[25] > 1.5 * up[5] and down[25] < down[5] / 1.5


def test_study_draws_have_the_wanted_spread(spark):
    rows = spark.range(800).select(noise.exact_sums(F.col("id").cast("string"), F.lit(3.0), F.lit(4)).alias("x")).collect()
    assert statistics.stdev(r.x for r in rows) == pytest.approx(6, rel=0.1) and abs(statistics.fmean(r.x for r in rows)) < 1


def test_equal_memory_and_bins(spark, smoke_dir):
    from unioncount.registry import QUERIES

    got = {r.kind: r for r in QUERIES["acc_equal_memory"](spark, smoke_dir).collect()}
    assert got["mr"].aare < got["zc"].aare < got["fz"].aare and max(r.bits for r in got.values()) <= 1.01 * min(r.bits for r in got.values())


def test_spread_follows_the_formula(spark):
    n = 4000
    states = experiments.hashed_states(experiments.generated(spark, n), n, 200, (256,))
    got = measures.accuracy_summary(experiments.estimates(states).where("kind = 'zc'"), ["m"]).first()
    assert got.rse == pytest.approx(theory.zc_rse(n, 256), rel=0.15) and abs(got.bias) < 0.02


def test_register_offset(spark):
    p = SketchParams(256, 12)
    df = rows(spark, 8000)
    ratio = []
    for offset in (0, 1):
        s = sketches.register_sums(sketches.merge(sketches.mr_sketch(df, p, offset=offset)), p)
        ratio.append(s.select(mr_estimate(F.col("harmonic"), F.col("empty"), p.m).alias("e")).first().e / 8000)
    assert ratio[0] == pytest.approx(0.5, abs=0.1) and ratio[1] == pytest.approx(1, abs=0.2)


def test_simulated_states_agree_with_formulas_and_hashing(spark):
    n, m = 10**6, 1024
    w = choose_width("zc", n, m)
    z = [r.z for r in experiments.simulated_states(spark, n, 60, (m,)).collect()]
    assert statistics.fmean(z) == pytest.approx(theory.zc_pois_mean(n, m, w), rel=0.01)
    n = 50_000
    drawn, hashed = experiments.simulated_states(spark, n, 60, (m,)), experiments.hashed_states(experiments.generated(spark, n), n, 60, (m,))
    for part in ("z", "total", "harmonic"):
        a, b = ([r[0] for r in x.select(part).collect()] for x in (drawn, hashed))
        spread = math.sqrt((statistics.variance(a) + statistics.variance(b)) / 60)
        assert abs(statistics.fmean(a) - statistics.fmean(b)) < 5 * spread, part
    drawn, hashed = experiments.fz_states(spark, 1000, 60, (64,)), experiments.hashed_fz(experiments.generated(spark, 1000), 1000, 60, 64, choose_width("fz", 1000, 64))
    a, b = ([r.z_star for r in x.collect()] for x in (drawn, hashed))
    assert abs(statistics.fmean(a) - statistics.fmean(b)) < 5 * math.sqrt((statistics.variance(a) + statistics.variance(b)) / 60)
    assert statistics.stdev(a) == pytest.approx(statistics.stdev(b), rel=0.4)


def test_cost_model_stays_in_the_published_range():
    for n in (10**3, 10**5, 10**7, 10**9):
        for m in (1024, 4096):
            for c in range(2, 8):
                zc, fz = measures.comm_cost("zc", n, m, 20, c), measures.comm_cost("fz", n, m, 20, c)
                assert 1.3 < fz["online_bytes"] / zc["online_bytes"] < 6 and 1.3 < fz["offline_bytes"] / zc["offline_bytes"] < 6
    assert measures.hash_ops("fz", 10, 4096) == 40960 and measures.sketch_bits("mr", 1024, 14) == 4096
    assert baselines.sortcmp_comparators(4) == 2 * 3 + 3


def test_audit_flags_only_absent_elements(spark):
    df = spark.createDataFrame([(str(i % 5), f"e{i}") for i in range(300)], PAIRS)
    got = audit.audit_membership(df, "0", ORACLE).first()
    assert got.wrongly_flagged == 0 and got.flagged > 0
    probes = spark.createDataFrame([(f"p{i}",) for i in range(200)], "element string")
    change = {r.kind: r.max_change for r in audit.empirical_sensitivity(df, probes, SketchParams(64, 12)).collect()}
    assert change["zc"] <= 1 < change["fz"]


def test_build_plan_is_one_exchange_without_python(spark, smoke_dir):
    df = sketches.merge(sketches.zc_sketch(sources.fixture("goods", spark, smoke_dir), ORACLE, ()))
    text = df._jdf.queryExecution().executedPlan().toString()
    assert text.count("partial_bit_or") >= 1 and "Python" not in text
    scan = [x for x in text.splitlines() if "ReadSchema" in x]
    assert len(scan) == 1 and "l_orderkey" in scan[0] and "l_extendedprice" not in scan[0]
    shape = measures.plan_shape(sketches.zc_sketch(sources.fixture("goods", spark, smoke_dir), ORACLE))
    assert shape["exchanges"] == 1 and shape["python"] == 0


def test_without_corpus_operators():
    """The library works where the corpus operators are not there: they are hidden from a new interpreter."""
    import subprocess
    import sys
    from pathlib import Path

    code = (
        "import sys\n"
        "class Hide:\n"
        "    def find_spec(self, name, path=None, target=None):\n"
        "        if name.startswith('unioncount.llm') or name == 'corpus_pipeline':\n"
        "            raise ModuleNotFoundError(name)\n"
        "sys.meta_path.insert(0, Hide())\n"
        "import __spark_entry__ as e\n"
        "q = e.queries()\n"
        "assert len(q) > 150 and not any(k.startswith('op') or k == 'pipeline' for k in q) and set(e.oracle_sql()) <= set(q)\n"
    )
    done = subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).resolve().parents[1], capture_output=True, text=True)
    assert done.returncode == 0, done.stderr
