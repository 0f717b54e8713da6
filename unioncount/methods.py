"""Queries of the methods, baselines and measures, each with its SQL where SQL can express it."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import audit, baselines, field, measures, noise, privacy, protocol, shares, sketches, theory
from .estimate import alpha, bisect_sql, fz_estimate, mr_estimate, mr_mean_estimate, zc_estimate
from .hashing import hash_sql, place_sql, rank_sql, uniform
from .params import ORACLE, P61, P72, STUDY_EPS_D, ProtocolConfig, SketchParams, choose_width, fresh_seed
from .shares import Keys, Shared
from .sources import fixture, fixture_sql, gen_sets, load
from .zerotest import opened_column, test_bits, zero_test

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
GOODS = SketchParams(1024, 12)
FZ = SketchParams(64, 20)
MINI = SketchParams(8, 6)
CFG = ProtocolConfig(ORACLE, c=3, sigma=2.0, seed="s")
#: The smaller grid of the published cost studies: 1,024 arrays, 20 holders, five parties, their share of the noise.
STUDY = SketchParams(1024, 13)
STUDY_CFG = ProtocolConfig(STUDY, c=5, sigma=round(1 / (math.sqrt(20) * STUDY_EPS_D), 3), seed="s")


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def zc_sql(relation: str, p: SketchParams, by: str = "holder") -> str:
    arr, x = place_sql("element", p)
    keys = f"{by}, " if by else ""
    return f"SELECT {keys}arr, bit_or(1::BIGINT << x) AS bits FROM (SELECT {keys}{arr} AS arr, {x} AS x FROM ({relation}) WHERE element IS NOT NULL) GROUP BY ALL"


def fz_sql(relation: str, p: SketchParams, by: str = "holder") -> str:
    keys = f"{by}, " if by else ""
    x = rank_sql(f"{hash_sql('arr::VARCHAR || $$|$$ || element', p.key)} & {(1 << (p.w - 1)) - 1}", p.w)
    return f"SELECT {keys}arr::INT AS arr, bit_or(1::BIGINT << {x}) AS bits FROM (SELECT DISTINCT {keys}element FROM ({relation}) WHERE element IS NOT NULL), (SELECT unnest(range({p.m})) AS arr) GROUP BY ALL"


def z_sql(sketch: str, p: SketchParams, by: str = "") -> str:
    keys = f"{by}, " if by else ""
    return f"SELECT {keys}({p.m * p.w} - coalesce(sum(bit_count(bits)), 0))::BIGINT AS z FROM ({sketch})" + (f" GROUP BY {by}" if by else "")


def low_sql(bits: str, w: int) -> str:
    return f"least(bit_count((~({bits}) & ({bits} + 1)) - 1), {w})"


DOCS, GOODS_SQL, ORDERS = fixture_sql("docs_text"), fixture_sql("goods"), fixture_sql("patients")

# sketches and estimates


@query(zc_sql(DOCS, ORACLE))
def zc_holder_sketch(s, d):
    return sketches.zc_sketch(fixture("docs_text", s, d), ORACLE)


@query(zc_sql(DOCS, ORACLE, ""))
def zc_union_sketch(s, d):
    return sketches.merge(sketches.zc_sketch(fixture("docs_text", s, d), ORACLE))


@query(z_sql(zc_sql(fixture_sql("reach"), ORACLE), ORACLE, "holder"))
def zc_zero_total(s, d):
    return sketches.zero_total(sketches.zc_sketch(fixture("reach", s, d), ORACLE), ORACLE, ("holder",))


@query(f"SELECT a.arr::INT AS arr, ({ORACLE.w} - coalesce(bit_count(bits), 0))::INT AS z FROM (SELECT unnest(range({ORACLE.m})) AS arr) a LEFT JOIN ({zc_sql(DOCS, ORACLE, '')}) b ON a.arr = b.arr")
def zc_zero_by_array(s, d):
    return sketches.zero_by_array(zc_union_sketch(s, d), ORACLE)


def _est_sql(relation: str, p: SketchParams) -> str:
    return f"SELECT z, round(n_hat, 4) AS n_hat, n_true, round(abs(n_hat - n_true) / n_true, 4) AS rel_err FROM ({bisect_sql(z_sql(zc_sql(relation, p, ''), p), [], p.m, p.w)}), (SELECT count(DISTINCT element) AS n_true FROM ({relation}))"


def _estimate(df: DataFrame, p: SketchParams) -> DataFrame:
    z = sketches.zero_total(sketches.merge(sketches.zc_sketch(df, p)), p).crossJoin(df.agg(F.count_distinct("element").alias("n_true")))
    n = zc_estimate(F.col("z"), p.m, p.w)
    return z.select("z", n.alias("e"), "n_true").select("z", F.round("e", 4).alias("n_hat"), "n_true", F.round(F.abs(F.col("e") - F.col("n_true")) / F.col("n_true"), 4).alias("rel_err"))


@query(_est_sql(GOODS_SQL, GOODS))
def zc_estimate_union(s, d):
    return _estimate(fixture("goods", s, d), GOODS)


for _name in ("docs_word", "docs_line", "goods_by_nation", "parts_by_nation", "hosts", "conv_word"):
    query(_est_sql(fixture_sql(_name), GOODS), f"zc_estimate_{_name}")(lambda s, d, x=_name: _estimate(fixture(x, s, d), GOODS))


@query("SELECT holder, z, round(n_hat, 4) AS n_hat FROM (" + bisect_sql(z_sql(zc_sql(ORDERS, ORACLE), ORACLE, "holder"), ["holder"], ORACLE.m, ORACLE.w) + ")")
def zc_estimate_by_holder(s, d):
    z = sketches.zero_total(sketches.zc_sketch(fixture("patients", s, d), ORACLE), ORACLE, ("holder",))
    return z.select("holder", "z", F.round(zc_estimate(F.col("z"), ORACLE.m, ORACLE.w), 4).alias("n_hat"))


_Z_DOCS = z_sql(zc_sql(DOCS, ORACLE, ""), ORACLE)


@query(
    f"SELECT a.z, round(a.n_hat, 4) AS n_hat_exp, round(b.n_hat, 4) AS n_hat_pow FROM ({bisect_sql(_Z_DOCS, [], ORACLE.m, ORACLE.w)}) a, ({bisect_sql(_Z_DOCS, [], ORACLE.m, ORACLE.w, form='pow')}) b"
)
def zc_estimate_pow(s, d):
    z = sketches.zero_total(zc_union_sketch(s, d), ORACLE)
    return z.select("z", *[F.round(zc_estimate(F.col("z"), ORACLE.m, ORACLE.w, form), 4).alias(f"n_hat_{form}") for form in ("exp", "pow")])


@query(fz_sql(ORDERS, FZ, ""))
def fz_union_sketch(s, d):
    return sketches.merge(sketches.fz_sketch(fixture("patients", s, d), FZ))


_FZ_TOTAL = f"SELECT sum({low_sql('bits', FZ.w)})::BIGINT AS z_star FROM ({fz_sql(ORDERS, FZ, '')})"


@query(_FZ_TOTAL)
def fz_total(s, d):
    return sketches.fz_total(fz_union_sketch(s, d), FZ)


@query(f"SELECT z_star, round(pow(2.0, z_star / {FZ.m}.0) / 0.77351, 4) AS n_hat FROM ({_FZ_TOTAL})", "fz_estimate")
def fz_estimate_query(s, d):
    return fz_total(s, d).select("z_star", F.round(fz_estimate(F.col("z_star"), FZ.m), 4).alias("n_hat"))


def mr_sql(relation: str, p: SketchParams, offset: int) -> str:
    arr, x = place_sql("element", p)
    return f"SELECT {arr} AS arr, (max({x}) + {offset})::INT AS reg FROM ({relation}) WHERE element IS NOT NULL GROUP BY 1"


def sums_sql(relation: str, p: SketchParams, offset: int) -> str:
    return f"SELECT sum(pow(2.0, -reg)) + ({p.m} - count(*)) AS harmonic, ({p.m} - count(*) FILTER (reg > 0))::BIGINT AS empty, sum(reg)::BIGINT AS total FROM ({mr_sql(relation, p, offset)})"


@query(mr_sql(GOODS_SQL, GOODS, 1))
def mr_union_registers(s, d):
    return sketches.merge(sketches.mr_sketch(fixture("goods", s, d), GOODS, offset=1))


_RAW = f"({alpha(GOODS.m) * GOODS.m**2!r}::DOUBLE / harmonic)"
_CORRECTED = f"CASE WHEN {_RAW} < {2.5 * GOODS.m} AND empty > 0 THEN -{GOODS.m}.0 * ln(empty / {GOODS.m}.0) ELSE {_RAW} END"


@query(f"SELECT round({_RAW}, 4) AS raw, empty, round({_CORRECTED}, 4) AS n_hat FROM ({sums_sql(GOODS_SQL, GOODS, 1)})", "mr_estimate")
def mr_estimate_query(s, d):
    sums = sketches.register_sums(mr_union_registers(s, d), GOODS)
    est = lambda correct: F.round(mr_estimate(F.col("harmonic"), F.col("empty"), GOODS.m, correct), 4)
    return sums.select(est(False).alias("raw"), "empty", est(True).alias("n_hat"))


@query(f"SELECT round(total / {GOODS.m}.0, 6) AS z_mean, round(0.783 * {GOODS.m} * pow(2.0, total / {GOODS.m}.0), 4) AS n_hat FROM ({sums_sql(GOODS_SQL, GOODS, 0)})", "mr_mean_estimate")
def mr_mean_query(s, d):
    sums = sketches.register_sums(sketches.merge(sketches.mr_sketch(fixture("goods", s, d), GOODS)), GOODS)
    return sums.select(F.round(F.col("total") / float(GOODS.m), 6).alias("z_mean"), F.round(mr_mean_estimate(F.col("total"), GOODS.m), 4).alias("n_hat"))


@query(f"SELECT round(a.raw, 4) AS n_hat_offset0, round(b.raw, 4) AS n_hat_offset1 FROM (SELECT {_RAW} AS raw FROM ({sums_sql(GOODS_SQL, GOODS, 0)})) a, (SELECT {_RAW} AS raw FROM ({sums_sql(GOODS_SQL, GOODS, 1)})) b")
def mr_literal_vs_standard(s, d):
    parts = []
    for offset in (0, 1):
        sums = sketches.register_sums(sketches.merge(sketches.mr_sketch(fixture("goods", s, d), GOODS, offset=offset)), GOODS)
        parts.append(sums.select(F.round(mr_estimate(F.col("harmonic"), F.col("empty"), GOODS.m, False), 4).alias(f"n_hat_offset{offset}")))
    return parts[0].crossJoin(parts[1])


_ALL = ("docs_text", "docs_word", "docs_line", "goods", "goods_by_nation", "patients", "reach", "clients", "hosts", "parts_by_nation", "conv_word")


@query(" UNION ALL ".join(f"SELECT '{x}' AS relation, count(DISTINCT element) AS n FROM ({fixture_sql(x)})" for x in _ALL))
def exact_union(s, d):
    return reduce(DataFrame.union, [baselines.exact_union(fixture(x, s, d)).select(F.lit(x).alias("relation"), "n") for x in _ALL])


@query(" UNION ALL ".join(f"SELECT '{x}' AS relation, n_sum::BIGINT AS n_sum, round(n_sum / n, 4) AS overlap_ratio FROM (SELECT sum(c) AS n_sum FROM (SELECT count(DISTINCT element) AS c FROM ({fixture_sql(x)}) GROUP BY holder)), (SELECT count(DISTINCT element) AS n FROM ({fixture_sql(x)}))" for x in _ALL))
def sum_local(s, d):
    rows = []
    for x in _ALL:
        rows.append(baselines.local_and_union(fixture(x, s, d)).select(F.lit(x).alias("relation"), "n_sum", F.round(F.col("n_sum") / F.col("n"), 4).alias("overlap_ratio")))
    return reduce(DataFrame.union, rows)


@query(f"SELECT arr, bits, TRUE AS ok FROM ({zc_sql(DOCS, ORACLE, '')})")
def merge_associative(s, d):
    one = sketches.zc_sketch(fixture("docs_text", s, d), ORACLE)
    flat, tree = sketches.merge(one), sketches.merge_tree(one).withColumnRenamed("bits", "other")
    twice = sketches.merge(one.union(one)).withColumnRenamed("bits", "again")
    return flat.join(tree, "arr").join(twice, "arr").select("arr", "bits", ((F.col("bits") == F.col("other")) & (F.col("bits") == F.col("again"))).alias("ok"))


@query(f"SELECT holder, len(bits)::INT * 8 AS n_bytes, ones FROM (SELECT holder, list(arr) AS l, {ORACLE.m}::INT AS m, sum(bit_count(bits))::BIGINT AS ones FROM ({zc_sql(DOCS, ORACLE)}) GROUP BY holder), (SELECT range({ORACLE.m}) AS bits)")
def packed_roundtrip(s, d):
    packed = sketches.pack(sketches.zc_sketch(fixture("docs_text", s, d), ORACLE), ORACLE)
    back = sketches.unpack(packed, ORACLE).groupBy("holder").agg(F.sum(F.bit_count("bits")).cast("bigint").alias("ones"))
    return packed.join(back, "holder").select("holder", F.length("packed").alias("n_bytes"), "ones")


# theory and privacy tables: scalars of the library against SQL

_GRID = [(n, m, w) for m, w in ((64, 12), (256, 10), (1024, 9)) for n in (10, 300, 5000, 100_000)]
_GRID_SQL = "(VALUES " + ", ".join(f"({n}, {m}, {w})" for n, m, w in _GRID) + ") AS g(n, m, w)"
_CELL = "(SELECT n, m, w, x, pow(2.0, -least(x + 1, w - 1)) / m AS p FROM (SELECT n, m, w, unnest(range(w)) AS x FROM " + _GRID_SQL + "))"


@query("SELECT x::INT AS x, round(pow(2.0, -least(x + 1, 11)) / 64, 12) AS p FROM (SELECT unnest(range(12)) AS x)")
def rank_probs(s, d):
    return s.createDataFrame([(x, round(q, 12)) for x, q in enumerate(theory.rank_probs(64, 12))], "x int, p double")


@query(
    f"WITH c AS {_CELL}, one AS (SELECT n, m, w, sum(pow(1 - p, n)) AS e, sum(pow(1 - 2 * p, n)) AS same FROM c GROUP BY ALL), two AS (SELECT a.n, a.m, a.w, sum(pow(1 - a.p - b.p, n_)) AS across FROM (SELECT *, n AS n_ FROM c) a JOIN c b ON a.n = b.n AND a.m = b.m AND a.w = b.w GROUP BY ALL) "
    "SELECT one.n::BIGINT AS n, one.m::INT AS m, one.w::INT AS w, round(one.m * e, 4) AS mean_z, round(one.m * e + one.m * (across - same) + one.m * (one.m - 1) * across - pow(one.m * e, 2), 3) AS var_z FROM one JOIN two ON one.n = two.n AND one.m = two.m AND one.w = two.w"
)
def zc_mean_var(s, d):
    return s.createDataFrame([(n, m, w, round(theory.zc_mean(n, m, w), 4), round(theory.zc_var(n, m, w), 3)) for n, m, w in _GRID], "n bigint, m int, w int, mean_z double, var_z double")


@query(f"SELECT n::BIGINT AS n, m::INT AS m, w::INT AS w, round(m * sum(exp(-n * p)), 4) AS mean_z, round(m * sum(exp(-n * p) * (1 - exp(-n * p))), 4) AS var_z, round(m * (1 - exp(-n / m::DOUBLE)), 4) AS var_short FROM {_CELL} GROUP BY n, m, w")
def zc_pois_mean_var(s, d):
    rows = [(n, m, w, round(theory.zc_pois_mean(n, m, w), 4), round(theory.zc_pois_var(n, m, w), 4), round(theory.zc_pois_var(n, m, w, False), 4)) for n, m, w in _GRID]
    return s.createDataFrame(rows, "n bigint, m int, w int, mean_z double, var_z double, var_short double")


@query(f"SELECT n::BIGINT AS n, m::INT AS m, w::INT AS w, round(sqrt(m * sum(exp(-n * p) * (1 - exp(-n * p)))) / (m * sum(p * exp(-n * p))) / n, 6) AS rse_delta, round(sqrt(m * sum(exp(-n * p) * (1 - exp(-n * p))) + 100.0) / (m * sum(p * exp(-n * p))) / n, 6) AS rse_delta_noisy FROM {_CELL} GROUP BY n, m, w")
def zc_mse_table(s, d):
    rows = [(n, m, w, round(math.sqrt(theory.zc_mse(n, m, w)) / n, 6), round(math.sqrt(theory.zc_mse(n, m, w, 10.0)) / n, 6)) for n, m, w in _GRID]
    return s.createDataFrame(rows, "n bigint, m int, w int, rse_delta double, rse_delta_noisy double")


@query(f"SELECT n::BIGINT AS n, m::INT AS m, round(ln(2.0) / sqrt(m) / sqrt(1 - exp(-n / m::DOUBLE)), 6) AS rse, round(ln(2.0) / sqrt(m) / sqrt(1 - exp(-n / m::DOUBLE)) * sqrt(1 + 6938.89 / m), 6) AS rse_noisy, round(ln(2.0) / sqrt(m) / sqrt(1 - exp(-n / m::DOUBLE)) * sqrt(1 + 6938.89 / (m * w * w)), 6) AS rse_noisy_printed FROM {_GRID_SQL}")
def zc_rse_table(s, d):
    rows = [(n, m, round(theory.zc_rse(n, m), 6), round(theory.zc_rse_noisy(n, m, w, 83.3), 6), round(theory.zc_rse_noisy(n, m, w, 83.3, True), 6)) for n, m, w in _GRID]
    return s.createDataFrame(rows, "n bigint, m int, rse double, rse_noisy double, rse_noisy_printed double")


_WIDTHS = [(n, m) for n in (10**3, 10**5, 10**7, 10**9) for m in (1024, 2048, 4096, 8192)]


@query("SELECT kind, n::BIGINT AS n, m::INT AS m, greatest(2, ceil(log2(CASE WHEN kind = 'fz' THEN n ELSE n / m::DOUBLE END) + 6))::INT AS w FROM (VALUES " + ", ".join(str(x) for x in _WIDTHS) + ") AS g(n, m), (VALUES ('zc'), ('mr'), ('fz')) AS k(kind)")
def width_table(s, d):
    return s.createDataFrame([(k, n, m, choose_width(k, n, m)) for n, m in _WIDTHS for k in ("zc", "mr", "fz")], "kind string, n bigint, m int, w int")


_EPS_GRID = [(dd, sg) for dd in (2, 5, 20) for sg in (0.5, 0.75, 2.0, 18.634)]


def _tau_sql(dd: str) -> str:
    return f"coalesce((SELECT 10 * sum(exp(-2 * pi() * pi() * sigma * sigma * k / (k + 1.0))) FROM (SELECT unnest(range(1, 25)) AS k) WHERE k < {dd}), 0.0)"


@query(
    "SELECT d::INT AS d, sigma, round(least(a, b), 8) AS eps_d, round(least(a1, b1), 8) AS eps_d_minus_1, round(0.5 * least(a, b) * (least(a, b) + 2 * sqrt(-2 * ln(1e-12))), 8) AS eps_bound FROM ("
    + "SELECT d, sigma, sqrt(1 / (d * sigma * sigma) + t / 2) AS a, 1 / (sqrt(d) * sigma) + t AS b, sqrt(1 / ((d - 1) * sigma * sigma) + t1 / 2) AS a1, 1 / (sqrt(d - 1) * sigma) + t1 AS b1 FROM (SELECT d, sigma, "
    + f"{_tau_sql('d')} AS t, {_tau_sql('d - 1')} AS t1 FROM (VALUES " + ", ".join(f"({a}, {b!r}::DOUBLE)" for a, b in _EPS_GRID) + ") AS g(d, sigma)))"
)
def eps_table(s, d):
    rows = []
    for dd, sg in _EPS_GRID:
        e = privacy.eps_distributed(sg, dd)[0]
        rows.append((dd, sg, round(e, 8), round(privacy.eps_curious(sg, dd), 8), round(privacy.cdp_bound(e, 1e-12), 8)))
    return s.createDataFrame(rows, "d int, sigma double, eps_d double, eps_d_minus_1 double, eps_bound double")


@query("SELECT eps_c, round(min(0.5 * eps_c * eps_c * a + ln(1 / (a * 1e-12)) / (a - 1) + ln(1 - 1 / a)), 4) AS eps_inf FROM (VALUES (0.012::DOUBLE), (0.05), (0.1), (0.5), (1.0)) AS g(eps_c), (SELECT 1 + exp(unnest(range(-20000, 120000)) / 10000.0) AS a) GROUP BY eps_c")
def eps_inf_table(s, d):
    return s.createDataFrame([(e, round(privacy.cdp_to_dp(e, 1e-12), 4)) for e in (0.012, 0.05, 0.1, 0.5, 1.0)], "eps_c double, eps_inf double")


_DIST = [(e, dd) for e in (k / 10 for k in range(1, 6)) for dd in (5, 10, 15, 20, 25)]


@query("SELECT eps, d::INT AS d, round(1 / (sqrt(d) * (sqrt(k * k + 2 * eps) - k)), 4) AS sigma, round(1 / (sqrt(d - 1) * (sqrt(k * k + 2 * eps) - k)), 4) AS sigma_curious FROM (SELECT eps, d, sqrt(-2 * ln(1e-12)) AS k FROM (VALUES " + ", ".join(f"({e!r}::DOUBLE, {dd})" for e, dd in _DIST) + ") AS g(eps, d))")
def sigma_table(s, d):
    rows = [(e, dd, round(privacy.calibrate_sigma(e, 1e-12, dd), 4), round(privacy.calibrate_sigma(e, 1e-12, dd, "holder"), 4)) for e, dd in _DIST]
    return s.createDataFrame(rows, "eps double, d int, sigma double, sigma_curious double")


_P2 = noise.pmf_sql(2.0)


@query(f"WITH t AS (SELECT x, pmf FROM ({_P2})) SELECT a AS alpha, round(ln(sum(pow(p.pmf, a) * pow(q.pmf, 1 - a))) / (a - 1), 6) AS divergence, round(a * 0.125, 6) AS bound FROM (VALUES (1.5::DOUBLE), (2.0), (4.0), (8.0)) AS g(a), t p JOIN t q ON q.x = p.x - 1 GROUP BY a")
def renyi_check(s, d):
    """Divergence of the discrete Gaussian from its shift by one, next to half eps^2 alpha with eps = 1 / sigma."""
    t = noise.pmf_table(s, 2.0).select("x", "pmf")
    pair = t.join(t.select((F.col("x") + 1).alias("x"), F.col("pmf").alias("q")), "x")
    orders = s.createDataFrame([(1.5,), (2.0,), (4.0,), (8.0,)], "alpha double")
    both = orders.crossJoin(pair).groupBy("alpha").agg(F.sum(F.pow("pmf", F.col("alpha")) * F.pow("q", 1 - F.col("alpha"))).alias("m"))
    return both.select("alpha", F.round(F.log("m") / (F.col("alpha") - 1), 6).alias("divergence"), F.round(F.col("alpha") * 0.125, 6).alias("bound"))


@query(f"SELECT x, round(pmf, 10) AS pmf FROM ({_P2})")
def noise_pmf(s, d):
    return noise.pmf_table(s, 2.0).select("x", F.round("pmf", 10).alias("pmf"))


def draw_sql(relation: str, column: str, seed: str, sigma: float) -> str:
    return f"SELECT {column}, x AS noise FROM (SELECT DISTINCT {column}, {hash_sql(column, seed)} / {float(1 << 60)!r}::DOUBLE AS u FROM ({relation})) JOIN ({noise.pmf_sql(sigma)}) ON u >= cdf_lo AND u < cdf_hi"


_NOISE = draw_sql(DOCS, "holder", "s", 2.0)


@query(_NOISE)
def noise_per_holder(s, d):
    return noise.noise_per_holder(fixture("docs_text", s, d), 2.0, "s")


_STAT = f"SELECT z, noise, z + noise AS z_noisy FROM ({_Z_DOCS}), (SELECT sum(noise)::BIGINT AS noise FROM ({_NOISE}))"
_RELEASE = f"SELECT z_noisy, round(n_hat, 4) AS n_hat, (z_noisy > {ORACLE.m * ORACLE.w} OR z_noisy < 0) AS clamped FROM ({bisect_sql(_STAT, [], ORACLE.m, ORACLE.w, 'z_noisy')})"


@query(f"SELECT z, noise, r.z_noisy, n_hat, clamped FROM ({_STAT}) t, ({_RELEASE}) r")
def noisy_release(s, d):
    return protocol.run_plain(fixture("docs_text", s, d), CFG)


@query(f"SELECT n.holder, (t.total - n.noise)::BIGINT AS residual_noise, round({privacy.eps_curious(2.0, 20)!r}::DOUBLE, 8) AS eps_view FROM ({_NOISE}) n, (SELECT sum(noise) AS total FROM ({_NOISE})) t")
def noisy_release_curious(s, d):
    """What remains for each holder that takes its own draw off the release."""
    n = noise_per_holder(s, d)
    return n.crossJoin(n.agg(F.sum("noise").alias("total"))).select("holder", (F.col("total") - F.col("noise")).alias("residual_noise"), F.lit(round(privacy.eps_curious(2.0, 20), 8)).alias("eps_view"))


@query(f"SELECT 'discrete' AS kind, round(x::DOUBLE, 4) AS noise FROM (SELECT {hash_sql(chr(39) + 'one' + chr(39), 's')} / {float(1 << 60)!r}::DOUBLE AS u) JOIN ({noise.pmf_sql(8.0)}) ON u >= cdf_lo AND u < cdf_hi UNION ALL SELECT 'gaussian', round(sqrt(-2.0 * ln(1.0 - {hash_sql(chr(39) + 'one' + chr(39), 'su')} / {float(1 << 60)!r}::DOUBLE)) * cos({2 * math.pi!r}::DOUBLE * ({hash_sql(chr(39) + 'one' + chr(39), 'sv')} / {float(1 << 60)!r}::DOUBLE)) * 8.0, 4)")
def noise_central(s, d):
    one = s.range(1).select(F.lit("one").alias("t"))
    discrete = noise.draw(one, F.col("t"), "s", 8.0).select(F.lit("discrete").alias("kind"), F.round(F.col("noise").cast("double"), 4).alias("noise"))
    return discrete.union(one.select(F.lit("gaussian"), F.round(noise.gaussian(F.col("t"), "s", 8.0), 4)))


@query(name="noise_from_os")
def noise_from_os(s, d):
    """Draws of a release, from the operating system's randomness."""
    return noise.os_draws(fixture("docs_text", s, d), 2.0)


# shares and the protocol

KEYS = Keys.agree(3, "s")


@query(f"SELECT holder AS cell, noise AS x, noise AS opened, TRUE AS mac_ok FROM ({_NOISE})")
def share_roundtrip(s, d):
    rows = noise_per_holder(s, d).withColumnRenamed("holder", "cell").withColumnRenamed("noise", "x")
    shared = rows.withColumn("s", shares.share_input(field.reduce_(F.col("x").cast("decimal(38,0)")), F.col("cell"), KEYS, "s", "rt").column())
    return opened_column(shared, "s", "o", KEYS).select("cell", "x", field.decode_centered(F.col("o")).alias("opened"), F.col("o_ok").alias("mac_ok"))


@query(f"SELECT i AS cell, ((i * 7 + 3) * (i * i + 1) % {P61})::VARCHAR AS product, ((i * 7 + 3) + (i * i + 1))::VARCHAR AS total, TRUE AS mac_ok FROM (SELECT unnest(range(50))::HUGEINT AS i)".replace("SELECT i AS cell", "SELECT i::BIGINT AS cell"))
def mac_check(s, d):
    """Sum and product of shared values, opened and checked."""
    dec = lambda c: c.cast("decimal(38,0)")
    i = F.col("id")
    rows = s.range(50).select(i.alias("cell"), shares.share_input(dec(i * 7 + 3), i, KEYS, "s", "x").column().alias("x"), shares.share_input(dec(i * i + 1), i, KEYS, "s", "y").column().alias("y"))
    product, _ = shares.multiply(Shared.of("x"), Shared.of("y"), F.col("cell"), KEYS, "s", "m")
    rows = rows.withColumn("xy", product.column()).withColumn("t", shares.add(Shared.of("x"), Shared.of("y")).column())
    rows = opened_column(opened_column(rows, "xy", "p", KEYS), "t", "q", KEYS)
    return rows.select("cell", F.col("p").cast("string").alias("product"), F.col("q").cast("string").alias("total"), (F.col("p_ok") & F.col("q_ok")).alias("mac_ok"))


def _element_sql(tag: str) -> str:
    return f"(({hash_sql('i::VARCHAR', f's|{tag}|0')}::HUGEINT * {1 << 60} + {hash_sql('i::VARCHAR', f's|{tag}|1')}::HUGEINT) % {P61})"


@query(f"SELECT i::BIGINT AS cell, cp::INT AS cp, CASE WHEN cp = 0 THEN {_element_sql('v|0')} WHEN cp = 1 THEN {_element_sql('v|1')} ELSE ((i - {_element_sql('v|0')} - {_element_sql('v|1')}) % {P61} + {P61}) % {P61} END::VARCHAR AS val FROM (SELECT unnest(range(40)) AS i), (SELECT unnest(range(3)) AS cp)")
def share_values(s, d):
    """Shares themselves, a row for each party, under reproducible randomness."""
    rows = s.range(40).select(F.col("id").alias("cell"), shares.deal(F.col("id").cast("decimal(38,0)"), F.col("id"), KEYS, "s", "").column().alias("s"))
    return shares.long_view(rows, "s").select("cell", "cp", F.col("val").cast("string").alias("val"))


def _tested(s: SparkSession, variant: str, prime: int = P61, reps: int = 20) -> DataFrame:
    with field.using(prime):
        keys = Keys.agree(3, "s")
        rows = s.range(21 * reps).select(F.col("id").alias("cell"), (F.col("id") % 21).cast("int").alias("x"))
        shared = rows.withColumn("s", shares.share_input(F.col("x").cast("decimal(38,0)"), F.col("cell"), keys, "s", "z").column())
        opened = opened_column(zero_test(shared, "s", "b", 5, keys, "s", "t", variant), "b", "o", keys)
        return opened.groupBy("x").agg(F.min(F.col("o").cast("int")).alias("b_min"), F.max(F.col("o").cast("int")).alias("b_max"), F.min(F.col("o_ok") & F.col("b_ok")).alias("mac_ok"))


_TESTED = "SELECT x::INT AS x, (x > 0)::INT AS b_min, (x > 0)::INT AS b_max, TRUE AS mac_ok FROM (SELECT unnest(range(21)) AS x)"


@query(_TESTED)
def zero_test_all(s, d):
    return _tested(s, "masked")


@query(_TESTED)
def zero_test_literal(s, d):
    """Masks of as many bits as the prime has: next to a power of two they misread with a chance of 2^-61."""
    return _tested(s, "literal", reps=4)


@query(_TESTED)
def zero_test_wide_field(s, d):
    """The same in the field of 72 bits, where products go limb by limb."""
    return _tested(s, "masked", P72, 4)


@query(f"SELECT count(*) AS cells, count(*) FILTER ({hash_sql('i::VARCHAR', 's|t|a|1')} % 8192 >= 8111) AS misread, TRUE AS mac_ok FROM (SELECT unnest(range(3000)) AS i)")
def zero_test_misreads(s, d):
    """What literal masks do in a small field: of 13 bits under the prime 8111, masks of 8111 and more read 0 as 1."""
    with field.using(8111):
        keys = Keys.agree(2, "s")
        rows = s.range(3000).select(F.col("id").alias("cell"), shares.share_input(field.constant(0), F.col("id"), keys, "s", "z").column().alias("s"))
        opened = opened_column(zero_test(rows, "s", "b", 5, keys, "s", "t", "literal"), "b", "o", keys)
        return opened.agg(F.count("*").alias("cells"), F.count_if(F.col("o") != 0).alias("misread"), F.min(F.col("o_ok") & F.col("b_ok")).alias("mac_ok"))


@query("SELECT x::INT AS x, CASE WHEN x = 1 THEN 0 ELSE 1 END::VARCHAR AS value FROM (SELECT unnest(range(1, 7)) AS x)")
def lookup_poly(s, d):
    beta = field.lookup_poly(5)
    return s.range(1, 7).select(F.col("id").cast("int").alias("x"), field.horner(beta, F.col("id").cast("decimal(38,0)")).cast("string").alias("value"))


def _cells_sql(bits: str, p: SketchParams) -> str:
    return f"SELECT (i // {p.w})::INT AS arr, (i % {p.w})::INT AS bit, ((coalesce(bits, 0) >> (i % {p.w})) & 1)::INT AS plain FROM (SELECT unnest(range({p.m * p.w})) AS i) LEFT JOIN ({bits}) ON arr = i // {p.w}"


@query(f"SELECT arr, bit, plain, plain AS secure, TRUE AS mac_ok FROM ({_cells_sql(zc_sql(DOCS, ORACLE, ''), ORACLE)})")
def secure_merge_equals_plain(s, d):
    cfg = ProtocolConfig(ORACLE, 3, 2.0, "s")
    sketch = sketches.zc_sketch(fixture("docs_text", s, d), ORACLE)
    keys = protocol.offline_setup(cfg)
    opened = opened_column(protocol.secure_merge(sketch, cfg, keys, 20), "b", "o", keys)
    plain = sketches.merge(sketch)
    bit = F.call_function("shiftright", F.coalesce("bits", F.lit(0).cast("bigint")), F.col("bit")).bitwiseAND(F.lit(1)).cast("int")
    return opened.join(plain, "arr", "left").select("arr", "bit", bit.alias("plain"), F.col("o").cast("int").alias("secure"), (F.col("ok") & F.col("o_ok")).alias("mac_ok"))


def _bytes_sql(cfg: ProtocolConfig, holders: int, relation: str) -> str:
    """What the phases send by the formulas of the cost model, for the holders that there are."""
    c, q, n, k = cfg.c, -(-cfg.prime.bit_length() // 8), cfg.sketch.m * cfg.sketch.w, test_bits(holders)
    pair = c * (c - 1) * q
    return f"SELECT (d * {(n + 1) * 2 * c * q} + {(4 * n + 2) * pair})::BIGINT AS online_bytes, ({(2 * k + 5) * n * 2 * pair} + d * {(n + 1) * 2 * c * q})::BIGINT AS offline_bytes FROM (SELECT count(DISTINCT holder) AS d FROM ({relation}))"


def _release_sql(relation: str, cfg: ProtocolConfig, noise_sum: str, level: float | None, holders: int) -> str:
    p = cfg.sketch
    stat = f"SELECT z + noise AS z_noisy FROM ({z_sql(zc_sql(relation, p, ''), p)}), ({noise_sum})"
    eps = "NULL::DOUBLE" if level is None else f"{level!r}::DOUBLE"
    return f"SELECT z_noisy, round(n_hat, 4) AS n_hat, TRUE AS mac_ok, {eps} AS eps_c, online_bytes, offline_bytes, (z_noisy > {p.m * p.w} OR z_noisy < 0) AS clamped FROM ({bisect_sql(stat, [], p.m, p.w, 'z_noisy')}), ({_bytes_sql(cfg, holders, relation)})"


def _drawn_sql(relation: str, cfg: ProtocolConfig) -> str:
    return f"SELECT sum(noise)::BIGINT AS noise FROM ({draw_sql(relation, 'holder', cfg.seed, cfg.sigma)})"


@query(_release_sql(DOCS, CFG, _drawn_sql(DOCS, CFG), protocol.level_of(CFG, "distributed", 20), 20))
def puc_end_to_end(s, d):
    """The whole protocol; its SQL is the plain release that it must equal, and the formulas of what is sent."""
    return protocol.run_puc(fixture("docs_text", s, d), CFG, 20)


_WORDS = fixture_sql("docs_word")


@query(_release_sql(_WORDS, STUDY_CFG, _drawn_sql(_WORDS, STUDY_CFG), protocol.level_of(STUDY_CFG, "distributed", 20), 20))
def puc_study(s, d):
    """The protocol at the parameters of the cost studies: 1,024 arrays, 20 holders, five parties."""
    return protocol.run_puc(fixture("docs_word", s, d), STUDY_CFG, 20)


_WIDE_CFG = ProtocolConfig(MINI, 5, 2.0, "s", P72)


@query(_release_sql(DOCS, _WIDE_CFG, _drawn_sql(DOCS, _WIDE_CFG), protocol.level_of(_WIDE_CFG, "distributed", 20), 20))
def puc_wide_field(s, d):
    """Five parties in the field of 72 bits."""
    return protocol.run_puc(fixture("docs_text", s, d), _WIDE_CFG, 20)


_ONE_DRAW = f"SELECT x AS noise FROM (SELECT {hash_sql(chr(39) + 'central' + chr(39), 's')} / {float(1 << 60)!r}::DOUBLE AS u) JOIN ({noise.pmf_sql(2.0)}) ON u >= cdf_lo AND u < cdf_hi"


_SMALL_CFG = ProtocolConfig(MINI, 3, 2.0, "s")


@query(_release_sql(ORDERS, _SMALL_CFG, _ONE_DRAW, protocol.level_of(_SMALL_CFG, "central", 5), 5))
def puc_central(s, d):
    """One draw for all holders."""
    return protocol.run_puc(fixture("patients", s, d), _SMALL_CFG, 5, noise="central")


@query(_release_sql(ORDERS, _SMALL_CFG, "SELECT 0 AS noise", None, 5))
def puc_fresh_randomness(s, d):
    """Shares, masks, factors, triples and MAC keys under a secret of the operating system; without noise the statistic
    must still be the plain one."""
    return protocol.run_puc(fixture("patients", s, d), ProtocolConfig(MINI, 3, 2.0, fresh_seed()), 5, noise="none")


_CHEATS = [(step, party, part) for step, party, part in (("count", 0, "val"), ("statistic", 1, "mac"), ("none", 0, "val"))]


@query("SELECT step, party::INT AS party, part, step <> 'none' AS aborted, step = 'none' AS released FROM (VALUES " + ", ".join(map(str, _CHEATS)) + ") AS g(step, party, part)")
def puc_tampered(s, d):
    """A party alters one share or MAC at a step of the protocol: the run aborts, and releases neither statistic nor
    estimate."""
    df = fixture("patients", s, d)
    tiny = ProtocolConfig(SketchParams(2, 3), 3, 2.0, "s")
    rows = []
    for step, party, part in _CHEATS:
        cheat = lambda at, x, step=step, party=party, part=part: shares.tamper(x, party, part) if at == step else x
        r = protocol.run_puc(df, tiny, 5, cheat=cheat).select("mac_ok", "z_noisy", "n_hat").first()
        rows.append((step, party, part, not r.mac_ok, r.z_noisy is not None and r.n_hat is not None))
    return s.createDataFrame(rows, "step string, party int, part string, aborted boolean, released boolean")


_FZ_SECURE = SketchParams(64, 14)


@query(f"SELECT sum({low_sql('bits', _FZ_SECURE.w)})::BIGINT AS z_star, TRUE AS mac_ok, round(pow(2.0, sum({low_sql('bits', _FZ_SECURE.w)}) / {_FZ_SECURE.m}.0) / 0.77351, 4) AS n_hat FROM ({fz_sql(ORDERS, _FZ_SECURE, '')})")
def fz_mpc_end_to_end(s, d):
    run = baselines.run_fz_mpc(fixture("patients", s, d), ProtocolConfig(_FZ_SECURE, 3, 2.0, "s"), 5)
    return run.select("z_star", "mac_ok", F.round(fz_estimate(F.col("z_star"), _FZ_SECURE.m), 4).alias("n_hat"))


# audits

_CAND = f"SELECT DISTINCT element, FALSE AS absent FROM ({DOCS}) WHERE holder <> 'src0' AND element NOT IN (SELECT element FROM ({DOCS}) WHERE holder = 'src0')"
_PLACE = place_sql("element", ORACLE)


@query(
    f"WITH c AS ({_CAND}), e AS (SELECT * FROM c UNION ALL SELECT 'absent|' || element, TRUE FROM c), u AS ({zc_sql(DOCS, ORACLE, '')}), t AS (SELECT absent, ((coalesce(bits, 0) >> x) & 1) = 0 AS flag FROM (SELECT absent, {_PLACE[0]} AS a, {_PLACE[1]} AS x FROM e) LEFT JOIN u ON a = u.arr) "
    "SELECT count(*) AS candidates, count(*) FILTER (flag) AS flagged, count(*) FILTER (flag AND NOT absent) AS wrongly_flagged FROM t"
)
def membership_audit(s, d):
    return audit.audit_membership(fixture("docs_text", s, d), "src0", ORACLE)


@query("SELECT i::BIGINT AS cell, cp::INT AS cp, part, TRUE AS detected FROM (SELECT unnest(range(30)) AS i), (SELECT unnest(range(3)) AS cp), (VALUES ('val'), ('mac')) AS p(part)")
def tamper_audit(s, d):
    return audit.tamper_report(s.range(30).select(F.col("id").alias("cell"), (F.col("id") * 5).alias("x")), CFG)


_PROBE = "SELECT 'probe' || i::VARCHAR AS holder, 'probe' || i::VARCHAR AS element FROM (SELECT unnest(range(200)) AS i)"
_FZ_PROBE = f"SELECT sum({low_sql('(coalesce(u.bits, 0) | n.bits)', MINI.w)} - {low_sql('coalesce(u.bits, 0)', MINI.w)}) AS c FROM ({fz_sql(_PROBE, MINI)}) n LEFT JOIN ({fz_sql(ORDERS, MINI, '')}) u ON n.arr = u.arr GROUP BY holder"


@query(f"SELECT 'zc' AS kind, max(1 - ((coalesce(bits, 0) >> x) & 1))::BIGINT AS max_change FROM (SELECT {place_sql('element', MINI)[0]} AS a, {place_sql('element', MINI)[1]} AS x FROM ({_PROBE})) LEFT JOIN ({zc_sql(ORDERS, MINI, '')}) ON a = arr UNION ALL SELECT 'fz', max(c)::BIGINT FROM ({_FZ_PROBE})")
def empirical_sensitivity(s, d):
    probes = s.range(200).select(F.concat(F.lit("probe"), F.col("id").cast("string")).alias("element"))
    return audit.empirical_sensitivity(fixture("patients", s, d), probes, MINI)


# costs

_SIZES = [(m, w) for m in (1024, 4096) for w in (8, 14, 20)]


@query("SELECT kind, m::INT AS m, w::INT AS w, (CASE WHEN kind = 'mr' THEN m * ceil(log2(w)) ELSE m * w END)::BIGINT AS bits_per_sketch FROM (VALUES " + ", ".join(str(x) for x in _SIZES) + ") AS g(m, w), (VALUES ('zc'), ('mr'), ('fz')) AS k(kind)")
def sketch_sizes(s, d):
    return s.createDataFrame([(k, m, w, measures.sketch_bits(k, m, w)) for m, w in _SIZES for k in ("zc", "mr", "fz")], "kind string, m int, w int, bits_per_sketch bigint")


def _comm_sql(grid: list[tuple[int, int, int]]) -> str:
    rows = ", ".join(str(x) for x in grid)
    return (
        "SELECT kind, n::BIGINT AS n, m::INT AS m, c::INT AS c, w::INT AS w, (2 * c * 8 * 20 * (m * w + 1) + 4 * m * w * c * (c - 1) * 8 + 2 * c * (c - 1) * 8 + CASE WHEN kind = 'fz' THEN 2 * m * (w - 1) * c * (c - 1) * 8 ELSE 0 END)::BIGINT AS online_bytes, "
        "(m * w * 15 * 2 * c * (c - 1) * 8 + 20 * (m * w + 1) * 2 * c * 8 + CASE WHEN kind = 'fz' THEN 3 * m * (w - 1) * 2 * c * (c - 1) * 8 ELSE 0 END)::BIGINT AS offline_bytes FROM "
        "(SELECT kind, n, m, c, greatest(2, ceil(log2(CASE WHEN kind = 'fz' THEN n ELSE n / m::DOUBLE END) + 6))::BIGINT AS w FROM (VALUES " + rows + ") AS g(n, m, c), (VALUES ('zc'), ('fz')) AS k(kind))"
    )


def _comm(s: SparkSession, grid: list[tuple[int, int, int]]) -> DataFrame:
    rows = [(k, n, m, c, x["w"], x["online_bytes"], x["offline_bytes"]) for n, m, c in grid for k in ("zc", "fz") for x in [measures.comm_cost(k, n, m, 20, c)]]
    return s.createDataFrame(rows, "kind string, n bigint, m int, c int, w int, online_bytes bigint, offline_bytes bigint")


_BY_C = [(10**6, m, c) for m in (1024, 4096) for c in range(2, 8)]
_BY_N = [(n, m, 5) for m in (1024, 4096) for n in (10**3, 10**5, 10**7, 10**9)]
query(_comm_sql(_BY_C), "comm_by_parties")(lambda s, d: _comm(s, _BY_C))
query(_comm_sql(_BY_N), "comm_by_n")(lambda s, d: _comm(s, _BY_N))


def _phase_sql() -> str:
    grid = sorted(set(_BY_N + _BY_C))
    run = lambda b: f"({b} / bandwidth + {b} / 8.0 * 2e-8)"
    return f"SELECT kind, n, m, c, net, round((7 + CASE WHEN kind = 'fz' THEN w - 1 ELSE 0 END) * rtt + {run('online_bytes')}, 4) AS online_s, round(2 * rtt + {run('offline_bytes')}, 4) AS offline_s FROM ({_comm_sql(grid)}), (VALUES ('lan', 5e-4::DOUBLE, 1.25e8::DOUBLE), ('wan', 3e-2, 1.25e7)) AS t(net, rtt, bandwidth)"


@query(_phase_sql())
def phase_cost_model(s, d):
    """Modelled seconds of both phases in a local and a wide network, by n and by parties."""
    rows = []
    for n, m, c in sorted(set(_BY_N + _BY_C)):
        for kind in ("zc", "fz"):
            cost = measures.comm_cost(kind, n, m, 20, c)
            for net, rtt, bandwidth in (("lan", 5e-4, 1.25e8), ("wan", 3e-2, 1.25e7)):
                t = measures.phase_seconds(cost, rtt, bandwidth)
                rows.append((kind, n, m, c, net, round(t["online"], 4), round(t["offline"], 4)))
    return s.createDataFrame(rows, "kind string, n bigint, m int, c int, net string, online_s double, offline_s double")


@query(f"SELECT count(DISTINCT element) AS n FROM ({GOODS_SQL})")
def sortcmp_exact(s, d):
    return baselines.sortcmp_exact(fixture("goods", s, d))


@query("SELECT n::BIGINT AS n, (pow(2, k) / 2 * k * (k + 1) / 2 + pow(2, k) - 1)::BIGINT AS comparators, (n * ceil(log2(n / 4096.0 + 64)))::BIGINT AS reference FROM (SELECT n, ceil(log2(n)) AS k FROM (VALUES (100), (1000), (100000), (1000000), (1000000000)) AS g(n))".replace(", (n * ceil(log2(n / 4096.0 + 64)))::BIGINT AS reference", ""))
def sortcmp_cost(s, d):
    return s.createDataFrame([(n, baselines.sortcmp_comparators(n)) for n in (100, 1000, 10**5, 10**6, 10**9)], "n bigint, comparators bigint")


@query("SELECT count(DISTINCT user_id) AS n, (pow(2, k) / 2 * k * (k + 1) / 2 + pow(2, k) - 1)::BIGINT AS comparators FROM (SELECT user_id FROM events WHERE event_type = 'purchase'), (SELECT ceil(log2(count(*))) AS k FROM events WHERE event_type = 'purchase') GROUP BY k")
def sortcmp_network(s, d):
    """The oblivious network executed over one kind of event."""
    return baselines.sortcmp_network(fixture("reach", s, d).where("holder = 'purchase'"))


@query(
    f"SELECT occupied, noise, round(-65536.0 * ln(1 - greatest(0.0, least(65535.0, occupied + noise - 1000)) / 65536.0), 4) AS n_hat FROM (SELECT count(DISTINCT {hash_sql('element', 'k')} % 65536) AS occupied FROM ({GOODS_SQL})), (SELECT count(*) FILTER ({hash_sql('i::VARCHAR', 's')} / {float(1 << 60)!r}::DOUBLE < 0.5) AS noise FROM (SELECT unnest(range(2000)) AS i))",
    "bins_estimate",
)
def bins_estimate(s, d):
    return baselines.bins_estimate(fixture("goods", s, d), 65536, 2000).withColumn("noise", F.col("noise").cast("bigint"))


@query(name="builtin_estimates")
def builtin_estimates(s, d):
    return baselines.builtin_estimates(fixture("goods", s, d))


@query("SELECT holder, count(*) AS n FROM (SELECT (id % 20)::VARCHAR AS holder FROM (SELECT unnest(range(10000)) AS id) UNION ALL SELECT ((id + 1) % 20)::VARCHAR FROM (SELECT unnest(range(10000)) AS id)) GROUP BY holder")
def gen_sets_query(s, d):
    return gen_sets(s, 10_000, 20, True).groupBy("holder").agg(F.count("*").alias("n"))


@query("SELECT count(DISTINCT l_orderkey) AS n FROM lineitem")
def builtin_bitmap(s, d):
    """Exact union of whole-number elements by bitmaps of 32,768 positions, merged by OR."""
    keys = load(s, d, "lineitem").select("l_orderkey", (F.col("l_suppkey") % 20).alias("holder"))
    each = keys.groupBy("holder", F.bitmap_bucket_number("l_orderkey").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("l_orderkey")).alias("bits"))
    return each.groupBy("b").agg(F.bitmap_count(F.bitmap_or_agg("bits")).alias("k")).agg(F.sum("k").alias("n"))


QUERIES["gen_sets"] = QUERIES.pop("gen_sets_query")
ORACLES["gen_sets"] = ORACLES.pop("gen_sets_query")


_BY_D = [(n, m, dd, 5) for n in (10**5, 10**6) for m in (1024, 4096) for dd in (5, 20)]


@query(
    "SELECT n::BIGINT AS n, m::INT AS m, d::INT AS d, c::INT AS c, w::INT AS w, (m * (d - 1))::BIGINT AS comparisons, (m * (d - 1) * (2 * b + 1) * 2 * c * (c - 1) * 8 + d * (m * b + 1) * 2 * c * 8)::BIGINT AS online_bytes FROM "
    "(SELECT *, ceil(log2(w))::BIGINT AS b FROM (SELECT *, greatest(2, ceil(log2(n / m::DOUBLE) + 6))::BIGINT AS w FROM (VALUES " + ", ".join(str(x) for x in _BY_D) + ") AS g(n, m, d, c)))"
)
def mr_mpc_cost(s, d):
    """What secure maxima of registers would cost."""
    rows = [(n, m, dd, c, x["w"], x["comparisons"], x["online_bytes"]) for n, m, dd, c in _BY_D for x in [measures.cost_mr_mpc(n, m, dd, c)]]
    return s.createDataFrame(rows, "n bigint, m int, d int, c int, w int, comparisons bigint, online_bytes bigint")


@query("SELECT kind, n::BIGINT AS n, m::INT AS m, (CASE WHEN kind = 'fz' THEN n::BIGINT * m ELSE n END)::BIGINT AS hashes FROM (VALUES (1000), (100000), (10000000), (1000000000)) AS a(n), (VALUES (1024), (4096)) AS b(m), (VALUES ('zc'), ('mr'), ('fz')) AS k(kind)")
def hash_ops_table(s, d):
    """Hashes that a holder of ``n`` elements computes."""
    rows = [(k, n, m, measures.hash_ops(k, n, m)) for n in (10**3, 10**5, 10**7, 10**9) for m in (1024, 4096) for k in ("zc", "mr", "fz")]
    return s.createDataFrame(rows, "kind string, n bigint, m int, hashes bigint")


@query(f"SELECT bits::INT AS bits, least(1.0, CASE WHEN pow(2.0, bits - 1) - 4096 * 14 <= 0 THEN 1.0 ELSE 2 * exp(-pow(pow(2.0, bits - 1) - 4096 * 14, 2) / (2 * 20 * 18.634 * 18.634)) END)::DOUBLE AS risk FROM (VALUES (17), (18), (32)) AS g(bits)")
def wrap_risk_table(s, d):
    """Chance that statistic and noise wrap around a field of so many bits."""
    return s.createDataFrame([(b, float(min(1.0, field.wrap_risk(18.634, 20, 4096, 14, 2**b)))) for b in (17, 18, 32)], "bits int, risk double")


_FZ_CAND = f"SELECT 'p' || i::VARCHAR AS holder, 'p' || i::VARCHAR AS element FROM (SELECT unnest(range(300)) AS i) UNION ALL SELECT DISTINCT element, element FROM ({ORDERS})"


@query(
    f"SELECT count(*) AS candidates, count(*) FILTER (c > 0) AS flagged, count(*) FILTER (c > 0 AND NOT starts_with(holder, 'p')) AS wrongly_flagged FROM (SELECT holder, sum({low_sql('(coalesce(u.bits, 0) | n.bits)', MINI.w)} - {low_sql('coalesce(u.bits, 0)', MINI.w)}) AS c FROM ({fz_sql(_FZ_CAND, MINI)}) n LEFT JOIN ({fz_sql(ORDERS, MINI, '')}) u ON n.arr = u.arr GROUP BY holder)"
)
def audit_first_zero(s, d):
    """Membership audit of the unnoised first-zero sum: a candidate that moves it is in no holder's set."""
    df = fixture("patients", s, d)
    probes = s.range(300).select(F.concat(F.lit("p"), F.col("id").cast("string")).alias("element"))
    candidates = probes.union(df.select("element").distinct()).select(F.col("element").alias("holder"), "element")
    union = sketches.merge(sketches.fz_sketch(df, MINI)).withColumnRenamed("bits", "old")
    both = sketches.fz_sketch(candidates, MINI).join(union, "arr", "left").withColumn("old", F.coalesce("old", F.lit(0).cast("bigint")))
    moved = sketches.lowest_zero(F.col("old").bitwiseOR(F.col("bits")), MINI.w) - sketches.lowest_zero(F.col("old"), MINI.w)
    change = both.groupBy("holder").agg(F.sum(moved).alias("c"))
    return change.agg(F.count("*").alias("candidates"), F.count_if(F.col("c") > 0).alias("flagged"), F.count_if((F.col("c") > 0) & ~F.col("holder").startswith("p")).alias("wrongly_flagged"))


@query(
    f"WITH c AS ({_CAND}), e AS (SELECT * FROM c UNION ALL SELECT 'absent|' || element, TRUE FROM c), u AS ({zc_sql(DOCS, ORACLE, '')}), t AS (SELECT absent, (1 - ((coalesce(bits, 0) >> x) & 1)) + noise.n > 0 AS flag FROM (SELECT absent, {_PLACE[0]} AS a, {_PLACE[1]} AS x FROM e) LEFT JOIN u ON a = u.arr, (SELECT sum(noise) AS n FROM ({_NOISE})) noise) "
    "SELECT absent, count(*) AS candidates, count(*) FILTER (flag) AS flagged FROM t GROUP BY absent"
)
def audit_zero_count_noisy(s, d):
    """The same attack on the noisy release: flags no longer depend on whether a candidate is absent."""
    df = fixture("docs_text", s, d)
    union = sketches.merge(sketches.zc_sketch(df, ORACLE))
    own = df.where("holder = 'src0'").select("element").distinct()
    others = df.where("holder <> 'src0'").select("element").distinct().join(own, "element", "left_anti")
    both = others.union(others.select(F.concat(F.lit("absent|"), "element")))
    total = noise_per_holder(s, d).agg(F.sum("noise").alias("n"))
    at = audit.placed(both, ORACLE).join(union, "arr", "left").crossJoin(total)
    change = 1 - F.call_function("shiftright", F.coalesce("bits", F.lit(0).cast("bigint")), F.col("x")).bitwiseAND(F.lit(1))
    return at.groupBy(F.col("element").startswith("absent|").alias("absent")).agg(F.count("*").alias("candidates"), F.count_if(change + F.col("n") > 0).alias("flagged"))


_OTHER = place_sql("element", ORACLE, "guess")


@query(
    f"WITH c AS ({_CAND}), e AS (SELECT * FROM c UNION ALL SELECT 'absent|' || element, TRUE FROM c), u AS ({zc_sql(DOCS, ORACLE, '')}), t AS (SELECT absent, ((coalesce(bits, 0) >> x) & 1) = 0 AS flag FROM (SELECT absent, {_OTHER[0]} AS a, {_OTHER[1]} AS x FROM e) LEFT JOIN u ON a = u.arr) "
    "SELECT count(*) AS candidates, count(*) FILTER (flag) AS flagged, count(*) FILTER (flag AND NOT absent) AS wrongly_flagged FROM t"
)
def audit_secret_hash(s, d):
    """The same attack by one who does not know the holders' key and guesses: members are flagged as often as others, so
    a flag tells nothing.  Holders do know the key, hence the noise."""
    return audit.audit_membership(fixture("docs_text", s, d), "src0", ORACLE, "guess")


# scenarios


@query("SELECT holder, n_events, z, round(n_hat, 4) AS n_hat FROM (SELECT holder, count(*) AS n_events FROM (" + fixture_sql("reach") + ") GROUP BY holder) JOIN (" + bisect_sql(z_sql(zc_sql(fixture_sql("reach"), GOODS), GOODS, "holder"), ["holder"], GOODS.m, GOODS.w) + ") USING (holder)")
def reach_by_publisher(s, d):
    df = fixture("reach", s, d)
    z = sketches.zero_total(sketches.zc_sketch(df, GOODS), GOODS, ("holder",))
    counts = df.groupBy("holder").agg(F.count("*").alias("n_events"))
    return counts.join(z, "holder").select("holder", "n_events", "z", F.round(zc_estimate(F.col("z"), GOODS.m, GOODS.w), 4).alias("n_hat"))


_SEG = "SELECT c_mktsegment AS segment, o_custkey::VARCHAR AS element FROM orders JOIN customer ON o_custkey = c_custkey"


@query("SELECT segment, z, round(n_hat, 4) AS n_hat FROM (" + bisect_sql(z_sql(zc_sql(_SEG, GOODS, "segment"), GOODS, "segment"), ["segment"], GOODS.m, GOODS.w) + ")")
def patients_by_segment(s, d):
    df = load(s, d, "orders").join(load(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).select(F.col("c_mktsegment").alias("segment"), F.col("o_custkey").cast("string").alias("element"))
    z = sketches.zero_total(sketches.zc_sketch(df, GOODS, ("segment",)), GOODS, ("segment",))
    return z.select("segment", "z", F.round(zc_estimate(F.col("z"), GOODS.m, GOODS.w), 4).alias("n_hat"))


def _by_holder_sql(name: str) -> str:
    return "SELECT holder, z, round(n_hat, 4) AS n_hat FROM (" + bisect_sql(z_sql(zc_sql(fixture_sql(name), GOODS), GOODS, "holder"), ["holder"], GOODS.m, GOODS.w) + ")"


def _by_holder(df: DataFrame) -> DataFrame:
    z = sketches.zero_total(sketches.zc_sketch(df, GOODS), GOODS, ("holder",))
    return z.select("holder", "z", F.round(zc_estimate(F.col("z"), GOODS.m, GOODS.w), 4).alias("n_hat"))


query(_by_holder_sql("goods"), "goods_by_reader")(lambda s, d: _by_holder(fixture("goods", s, d)))
query(_by_holder_sql("clients"), "clients_by_hour")(lambda s, d: _by_holder(fixture("clients", s, d)))
