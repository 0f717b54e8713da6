"""The accuracy and cost studies, on the given tables and on generated sets.

A run is a new hash key and new noise; ``RUNS`` is the published 100.  Zero-count arrays and registers are hashed for
sets of up to 10^5 elements and drawn cell by cell at their rates beyond; a first-zero sketch costs m hashes an element,
so its cells are drawn, and tests hold the draws against hashed sketches.  Noise is drawn holder by holder from the exact
discrete sampler.
"""

from __future__ import annotations

import math
import random
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, measures, noise, privacy
from .estimate import FZ_BIAS, MEAN_RANK, alpha_by_row, bisect_sql, zc_estimate, zc_estimate_by_row
from .hashing import rank_of
from .methods import low_sql, query
from .params import STUDY_DELTA, STUDY_EPS, STUDY_EPS_D, STUDY_M, choose_width
from .sketches import lowest_zero
from .sources import fixture, fixture_sql, load
from .storage import written_once
from .theory import zc_rse

RUNS = 100
SCALES = (10**3, 10**5, 10**7, 10**9)
#: Largest set whose elements are hashed once a run.
HASHED_MOST = 10**5
GRID_M, GRID_EPS, GRID_D = (1024, 2048, 4096, 8192), tuple(k / 10 for k in range(1, 6)), (5, 10, 15, 20, 25)


def generated(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").cast("string").alias("element"))


def eps_c(eps: float) -> float:
    """Concentrated level of the studies: .012 goes with .1, the others by the closed bound."""
    return STUDY_EPS_D if eps == STUDY_EPS else privacy.dp_to_cdp(eps, STUDY_DELTA)


def hashed_states(elements: DataFrame, n: int, runs: int, ms: tuple[int, ...], algo: str = "xx64", width: int | None = None) -> DataFrame:
    """``run, m, w, n, z, total, harmonic, empty``: statistics of the union's zero-count arrays and registers.

    One hash per element and run serves all sizes; registers are read off the arrays, whose highest bit is the rank.
    """
    spark = elements.sparkSession
    keys = spark.range(runs).select(F.col("id").cast("int").alias("run"))
    grid = F.array(*[F.struct(F.lit(m).alias("m"), F.lit(m.bit_length() - 1).alias("r"), F.lit(width or choose_width("zc", n, m)).alias("w")) for m in ms])
    text = F.concat(F.lit("r"), F.col("run").cast("string"), F.lit("|"), F.col("element"))
    h = F.xxhash64(text).bitwiseAND(F.lit((1 << 60) - 1)) if algo == "xx64" else F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")
    rows = elements.select("element").distinct().crossJoin(F.broadcast(keys)).select("run", h.alias("h"), F.explode(grid).alias("g"))
    high = F.call_function("shiftrightunsigned", F.col("h"), F.col("g.r")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("g.w") - 1) - 1)
    x = F.when(high == 0, F.col("g.w") - 1).otherwise(rank_of(high, 2))
    placed = rows.select("run", "g.m", "g.w", F.col("h").bitwiseAND(F.col("g.m") - 1).alias("arr"), F.call_function("shiftleft", F.lit(1).cast("bigint"), x).alias("bit"))
    arrays = placed.groupBy("run", "m", "w", "arr").agg(F.bit_or("bit").alias("bits"))
    top = F.floor(F.log2(F.col("bits").cast("double"))).cast("int")
    sums = arrays.groupBy("run", "m", "w").agg(F.sum(F.bit_count("bits")).alias("ones"), F.count("*").alias("used"), F.sum(top).alias("total"), F.sum(F.pow(F.lit(2.0), -(top + 1))).alias("h"))
    return sums.select("run", "m", "w", F.lit(n).cast("bigint").alias("n"), (F.col("m") * F.col("w") - F.col("ones")).cast("bigint").alias("z"), "total", (F.col("h") + F.col("m") - F.col("used")).alias("harmonic"), (F.col("m") - F.col("used")).alias("empty"))


_STATE = "run int, m int, w int, n bigint, z bigint, total bigint, harmonic double, empty bigint"


def simulated_states(spark: SparkSession, n: int, runs: int, ms: tuple[int, ...]) -> DataFrame:
    """What ``hashed_states`` gives, with each cell drawn on its own at its Poisson rate; for n / m of 3 or more."""
    kinds = pa.schema([("run", pa.int32()), ("m", pa.int32()), ("w", pa.int32()), *((c, pa.int64()) for c in ("n", "z", "total")), ("harmonic", pa.float64()), ("empty", pa.int64())])

    def draw(batches):
        for batch in batches:
            for run, m in zip(batch.column("run").to_pylist(), batch.column("m").to_pylist()):
                w = choose_width("zc", n, m)
                full = np.random.default_rng([n, m, run]).random((m, w)) >= np.exp(-n / m * 2.0 ** -np.minimum(np.arange(w) + 1, w - 1))
                used = full.any(axis=1)
                top = w - 1 - full[:, ::-1].argmax(axis=1)[used]
                row = {"run": run, "m": m, "w": w, "n": n, "z": int((~full).sum()), "total": int(top.sum()), "harmonic": float((2.0 ** -(top + 1.0)).sum() + (~used).sum()), "empty": int((~used).sum())}
                yield pa.RecordBatch.from_pylist([row], schema=kinds)

    return _each_run(spark, runs, ms).mapInArrow(draw, _STATE)


def _each_run(spark: SparkSession, runs: int, ms: tuple[int, ...]) -> DataFrame:
    sizes = F.array(*[F.lit(m) for m in ms])
    return spark.range(runs).select(F.col("id").cast("int").alias("run"), F.explode(sizes).alias("m")).repartition(8, "run", "m")


def fz_states(spark: SparkSession, n: int, runs: int, ms: tuple[int, ...]) -> DataFrame:
    """``run, m, w, n, z_star`` of first-zero sketches, each cell drawn on its own: every array sees all ``n`` elements."""

    def draw(batches):
        for batch in batches:
            for run, m in zip(batch.column("run").to_pylist(), batch.column("m").to_pylist()):
                w = choose_width("fz", n, m)
                zero = np.random.default_rng([n, m, run, 1]).random((m, w)) < np.exp(-n * 2.0 ** -np.minimum(np.arange(w) + 1, w - 1))
                lowest = np.where(zero.any(axis=1), zero.argmax(axis=1), w)
                yield pa.RecordBatch.from_pydict({"run": pa.array([run], pa.int32()), "m": pa.array([m], pa.int32()), "w": pa.array([w], pa.int32()), "n": [n], "z_star": [int(lowest.sum())]})

    return _each_run(spark, runs, ms).mapInArrow(draw, "run int, m int, w int, n bigint, z_star bigint")


def estimates(states: DataFrame) -> DataFrame:
    """``run, m, kind, n, n_hat`` without noise."""
    m, w = F.col("m"), F.col("w")
    raw = alpha_by_row(m) * m * m / F.col("harmonic")
    mr = F.when((raw < 2.5 * m) & (F.col("empty") > 0), -m * F.log(F.col("empty") / m)).otherwise(raw)
    mean = F.lit(MEAN_RANK) * m * F.pow(F.lit(2.0), F.col("total") / m)
    each = F.explode(F.create_map(F.lit("zc"), zc_estimate_by_row(F.col("z"), m, w), F.lit("mr"), mr, F.lit("mr_mean"), mean)).alias("kind", "n_hat")
    return states.select("run", "m", "n", each).select("run", "m", "kind", "n", "n_hat")


def fz_estimates(states: DataFrame) -> DataFrame:
    return states.select("run", "m", F.lit("fz").alias("kind"), "n", (F.pow(F.lit(2.0), F.col("z_star") / F.col("m")) / F.lit(FZ_BIAS)).alias("n_hat"))


def states_of(spark: SparkSession, n: int, elements: DataFrame | None = None, runs: int = RUNS, ms: tuple[int, ...] = GRID_M, name: str = "ids") -> tuple[DataFrame, DataFrame]:
    """Statistics of all runs and sizes (zero-count arrays with registers, first-zero sketches), written once a session."""
    made = elements if elements is not None else generated(spark, n)
    one = lambda: simulated_states(spark, n, runs, ms) if elements is None and n > HASHED_MOST else hashed_states(made, n, runs, ms)
    return written_once(spark, ("zc", name, n, runs, ms), one, "states"), written_once(spark, ("fz", n, runs, ms), lambda: fz_states(spark, n, runs, ms), "fz-states")


def plain_by_m(states: tuple[DataFrame, DataFrame]) -> DataFrame:
    return estimates(states[0]).unionByName(fz_estimates(states[1]))


#: How the noise of all holders together depends on their number: fixed for one level (each draws 1 / sqrt(d) of it),
#: or growing where each draws what one would need alone, or falling where each divides it by d.
SCALINGS = {"target_eps": 0.0, "per_holder": 0.5, "over_d": -0.5}


def noisy(states: tuple[DataFrame, DataFrame], mechanism: str, grid: list[tuple[float, int, int]], scaling: str = "target_eps") -> DataFrame:
    """``run, kind, n, m, d, eps, level, n_hat`` for every (eps, m, d) of the grid.

    The total noise deviation is sensitivity / level, times what ``SCALINGS`` says of d; ``gaussian`` is one continuous
    draw, ``discrete`` one exact discrete draw, ``distributed`` one of each holder.
    """
    spark = states[0].sparkSession
    power = SCALINGS[scaling]
    points = spark.createDataFrame([(float(e), m, d, float(eps_c(e)), float(d**power)) for e, m, d in grid], "eps double, m int, d int, level double, grow double")
    m, w, d = F.col("m"), F.col("w"), F.col("d")
    zc = states[0].join(F.broadcast(points), "m")
    fz = states[1].join(F.broadcast(points), "m")
    head = ["run", "n", "m", "w", "d", "eps", "level", "grow"]
    # registers are released as their sum, which moves by w - 1 at most; first-zero sums by w an array
    stats = reduce(DataFrame.union, [
        zc.select(*head, F.lit("zc").alias("kind"), F.col("z").alias("stat"), F.lit(1.0).alias("delta")),
        zc.select(*head, F.lit("mr_mean"), F.col("total"), (w - 1).cast("double")),
        fz.select(*head, F.lit("fz"), F.col("z_star"), (w * m).cast("double")),
    ])
    text = F.concat_ws("|", "kind", "eps", "m", "d", "n", "run")
    sd = F.col("delta") / F.col("level") * F.col("grow")
    if mechanism == "gaussian":
        u = lambda k: F.xxhash64(text, F.lit(k)).bitwiseAND(F.lit((1 << 53) - 1)) / F.lit(float(1 << 53))
        drawn = F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - u("u"))) * F.cos(F.lit(2 * math.pi) * u("v")) * sd
    elif mechanism == "discrete":
        drawn = noise.exact_sums(text, sd, F.lit(1))
    else:
        drawn = noise.exact_sums(text, sd / F.sqrt(d.cast("double")), d)
    value = F.col("stat") + F.col("noise")
    inside = F.least(F.greatest(value, F.lit(0.0)), (m * w).cast("double"))
    power_of = lambda factor: factor * F.pow(F.lit(2.0), inside / m)
    n_hat = F.when(F.col("kind") == "zc", zc_estimate_by_row(value, m, w)).when(F.col("kind") == "fz", power_of(F.lit(1 / FZ_BIAS))).otherwise(power_of(F.lit(MEAN_RANK) * m))
    return stats.withColumn("noise", drawn).select("run", "kind", "n", "m", "d", "eps", "level", n_hat.alias("n_hat"))


def _goods(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    goods = fixture("goods", s, d).select("element").distinct()
    n = goods.count()
    return states_of(s, n, goods, name=f"goods {d}")


def _words(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    words = fixture("docs_word", s, d).select("element").distinct()
    n = words.count()
    return states_of(s, n, words, name=f"words {d}", ms=(STUDY_M,))


def _all(s: SparkSession, d: str) -> list[tuple[DataFrame, DataFrame]]:
    return [*[states_of(s, n) for n in SCALES], _goods(s, d)]


def _union(states: list[tuple[DataFrame, DataFrame]]) -> tuple[DataFrame, DataFrame]:
    return reduce(DataFrame.union, [a for a, _ in states]), reduce(DataFrame.union, [b for _, b in states])


@query()
def acc_plain_by_m(s, d):
    """Error without privacy by number of arrays; all three sketches, n from 10^3 to 10^9 and the goods."""
    return measures.aare(plain_by_m(_union(_all(s, d))), ["n", "m", "kind"])


@query()
def acc_ratio_by_m(s, d):
    """Errors of the other sketches over that of the zero-count sketch."""
    return measures.ratio_table(acc_plain_by_m(s, d), ["n", "m"])


def _by_eps(s, d, mechanism):
    """``level`` is the concentrated level that goes with eps: .012 with .1 as published, the closed bound with others."""
    return measures.aare(noisy(_union(_all(s, d)), mechanism, [(eps, STUDY_M, 20) for eps in GRID_EPS]), ["n", "m", "eps", "level", "kind"])


def _by_m(s, d, mechanism):
    return measures.aare(noisy(_union(_all(s, d)), mechanism, [(STUDY_EPS, m, 20) for m in GRID_M]), ["n", "m", "eps", "level", "kind"])


query(None, "acc_central_by_eps")(lambda s, d: _by_eps(s, d, "gaussian"))
query(None, "acc_central_by_m")(lambda s, d: _by_m(s, d, "gaussian"))
query(None, "acc_central_discrete_by_eps")(lambda s, d: _by_eps(s, d, "discrete"))
query(None, "acc_dist_by_eps")(lambda s, d: _by_eps(s, d, "distributed"))
query(None, "acc_dist_by_m")(lambda s, d: _by_m(s, d, "distributed"))


@query()
def acc_dist_words_by_eps(s, d):
    """The same on the words of the documents, whose sources are the holders."""
    return measures.aare(noisy(_words(s, d), "distributed", [(eps, STUDY_M, 20) for eps in GRID_EPS]), ["n", "m", "eps", "level", "kind"])


@query()
def acc_dist_by_holders(s, d):
    """Error by number of holders under the three ways to scale their noise: the union stays, each holder draws."""
    states = _union([states_of(s, n) for n in SCALES])
    parts = [noisy(states, "distributed", [(STUDY_EPS, STUDY_M, h) for h in GRID_D], k).withColumn("scaling", F.lit(k)) for k in SCALINGS]
    return measures.aare(reduce(DataFrame.union, parts), ["n", "m", "d", "scaling", "kind"])


@query()
def acc_dist_by_nations(s, d):
    """Error by number of nations that take part: their union grows, and so does the number of draws."""
    rows = load(s, d, "lineitem").join(load(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).select("s_nationkey", F.col("l_orderkey").cast("string").alias("element")).distinct()
    rows = written_once(s, ("nations", d), lambda: rows, "nations")
    parts = []
    for h in GRID_D:
        part = rows.where(F.col("s_nationkey") < h).select("element").distinct()
        n = part.count()
        if n:
            parts.append(noisy(states_of(s, n, part, ms=(STUDY_M,), name=f"nations {h} {d}"), "distributed", [(STUDY_EPS, STUDY_M, h)]))
    return measures.aare(reduce(DataFrame.union, parts), ["n", "m", "d", "kind"])


@query()
def acc_equal_memory(s, d):
    """Errors at equal numbers of bits in place of equal numbers of arrays, n = 10^5: registers are small, so there are
    more of them."""
    n, w = HASHED_MOST, choose_width("zc", HASHED_MOST, 1024)
    bits = 1024 * w
    zc = estimates(states_of(s, n)[0].where("m = 1024")).where("kind = 'zc'").select("run", "kind", F.lit(1024).alias("m"), "n", "n_hat")
    wf = choose_width("fz", n, 1024)
    mf = bits // wf
    fz = fz_estimates(fz_states(s, n, RUNS, (mf,))).select("run", "kind", "m", "n", "n_hat")
    each = (w - 1).bit_length()
    mr = bits // each
    keys = s.range(RUNS).select(F.col("id").cast("int").alias("run"))
    h = F.xxhash64(F.lit("mem"), "run", "element")
    rest = F.xxhash64(F.lit("mem2"), "run", "element")
    rank = F.least(F.bit_count(rest.bitwiseAND(-rest) - 1).cast("int"), F.lit(w - 1)) + 1
    registers = generated(s, n).crossJoin(F.broadcast(keys)).select("run", F.pmod(h, F.lit(mr)).alias("arr"), rank.alias("r")).groupBy("run", "arr").agg(F.max("r").alias("r"))
    sums = registers.groupBy("run").agg(F.sum(F.pow(F.lit(2.0), -F.col("r"))).alias("h"), F.count("*").alias("used"))
    raw = alpha_by_row(F.lit(float(mr))) * float(mr) * float(mr) / (F.col("h") + mr - F.col("used"))
    other = sums.select("run", F.lit("mr").alias("kind"), F.lit(mr).alias("m"), F.lit(n).cast("bigint").alias("n"), raw.alias("n_hat"))
    size = F.when(F.col("kind") == "zc", 1024 * w).when(F.col("kind") == "fz", mf * wf).otherwise(mr * each).cast("bigint")
    return measures.aare(zc.union(fz).union(other), ["n", "kind", "m"]).withColumn("bits", size)


@query("SELECT d::INT AS d, count(DISTINCT l_orderkey) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN (VALUES (5), (10), (15), (20), (25)) AS g(d) ON s_nationkey < d GROUP BY d")
def union_by_holders(s, d):
    """Size of the union as more nations take part."""
    grid = s.createDataFrame([(x,) for x in GRID_D], "d int")
    rows = load(s, d, "lineitem").join(load(s, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).select("s_nationkey", "l_orderkey").distinct()
    return rows.join(F.broadcast(grid), F.col("s_nationkey") < F.col("d")).groupBy("d").agg(F.count_distinct("l_orderkey").alias("n"))


@query()
def acc_vs_bins(s, d):
    """Zero-count protocol against noisy bins at n of 20,000 to 50,000: both are run on the sets, with as many bins as the
    protocol has cells, and coins of each of five parties, any one of which may be the only honest one."""
    parts = []
    keys = s.range(RUNS).select(F.col("id").cast("int").alias("run"))

    @F.pandas_udf("bigint")
    def heads(texts: pd.Series, coins: pd.Series) -> pd.Series:
        return pd.Series([random.Random(t).binomialvariate(int(k), 0.5) for t, k in zip(texts, coins)], dtype="int64")

    levels = s.createDataFrame([(e, 5 * baselines.coins_for(e, STUDY_DELTA)) for e in (0.1, 0.3)], "eps double, coins bigint")
    for n in (20_000, 30_000, 40_000, 50_000):
        mine = noisy(states_of(s, n, ms=(STUDY_M,)), "distributed", [(e, STUDY_M, 20) for e in (0.1, 0.3)]).where("kind = 'zc'")
        parts.append(mine.select("run", "kind", "n", "eps", "n_hat"))
        bins = STUDY_M * choose_width("zc", n, STUDY_M)
        placed = generated(s, n).crossJoin(F.broadcast(keys)).select("run", F.pmod(F.xxhash64(F.lit("bins"), "run", "element"), F.lit(bins)).alias("b"))
        occupied = placed.distinct().groupBy("run").agg(F.count("*").alias("occupied")).crossJoin(F.broadcast(levels))
        seen = occupied.withColumn("heads", heads(F.concat_ws("|", F.lit(str(n)), "eps", "run"), "coins"))
        left = F.col("occupied") + F.col("heads") - F.col("coins") / 2
        e = -F.lit(float(bins)) * F.log(1 - F.least(F.greatest(left, F.lit(0.0)), F.lit(bins - 1.0)) / float(bins))
        parts.append(seen.select("run", F.lit("bins").alias("kind"), F.lit(n).cast("bigint").alias("n"), "eps", e.alias("n_hat")))
    return measures.aare(reduce(DataFrame.union, parts), ["n", "eps", "kind"])


def _runs_sql(relation: str, runs: int, m: int, w: int) -> str:
    h = "('0x' || substr(md5('r' || run::VARCHAR || '|' || element), 1, 15))::BIGINT"
    r = m.bit_length() - 1
    high = f"(({h} >> {r}) & {(1 << (w - 1)) - 1})"
    arrays = f"SELECT run, {h} & {m - 1} AS arr, bit_or(1::BIGINT << (CASE WHEN {high} = 0 THEN {w - 1} ELSE bit_count(({high} & -{high}) - 1) END)) AS bits FROM (SELECT DISTINCT element FROM ({relation})), (SELECT unnest(range({runs})) AS run) GROUP BY ALL"
    return f"SELECT run, ({m * w} - sum(bit_count(bits)))::BIGINT AS z FROM ({arrays}) GROUP BY run"


@query(
    f"SELECT 64::INT AS m, round(stddev_samp(n_hat) / any_value(n), 4) AS observed_rse, round({math.log(2) / 8!r}::DOUBLE / sqrt(1 - exp(-any_value(n) / 64.0)), 4) AS predicted_rse FROM (" + bisect_sql(_runs_sql(fixture_sql("docs_text"), 100, 64, 12), ["run"], 64, 12) + f"), (SELECT count(DISTINCT element) AS n FROM ({fixture_sql('docs_text')}))"
)
def theory_vs_observed(s, d):
    """Spread of the estimate over 100 keys, next to the formula."""
    df = fixture("docs_text", s, d)
    n = df.select("element").distinct().count()
    rows = hashed_states(df, n, 100, (64,), "md5", 12).select(zc_estimate(F.col("z"), 64, 12).alias("n_hat"))
    return rows.agg(F.round(F.stddev_samp("n_hat") / n, 4).alias("observed_rse")).select(F.lit(64).alias("m"), "observed_rse", F.lit(round(zc_rse(n, 64), 4)).alias("predicted_rse"))


_HASHED = [(64, 12), (256, 12), (1024, 12)]


@query(" UNION ALL ".join(f"SELECT {m}::INT AS m, round(avg(abs(n_hat - n) / n), 4) AS aare FROM (" + bisect_sql(_runs_sql(fixture_sql("docs_text"), 20, m, w), ["run"], m, w) + f"), (SELECT count(DISTINCT element) AS n FROM ({fixture_sql('docs_text')}))" for m, w in _HASHED))
def acc_hashed_by_m(s, d):
    """Error of the zero-count sketch over 20 keys, the same hashes on both engines."""
    df = fixture("docs_text", s, d)
    n = df.select("element").distinct().count()
    states = hashed_states(df, n, 20, tuple(m for m, _ in _HASHED), "md5", 12)
    return measures.aare(estimates(states).where("kind = 'zc'"), ["m"])


def _ranks_sql(relation: str, runs: int, m: int, w: int) -> str:
    h = "('0x' || substr(md5('r' || run::VARCHAR || '|' || element), 1, 15))::BIGINT"
    high = f"(({h} >> {m.bit_length() - 1}) & {(1 << (w - 1)) - 1})"
    top = f"SELECT run, {h} & {m - 1} AS arr, max(CASE WHEN {high} = 0 THEN {w - 1} ELSE bit_count(({high} & -{high}) - 1) END) AS top FROM (SELECT DISTINCT element FROM ({relation})), (SELECT unnest(range({runs})) AS run) GROUP BY ALL"
    return f"SELECT run, sum(pow(2.0, -(top + 1))) + ({m} - count(*)) AS harmonic, {m} - count(*) AS empty, sum(top)::BIGINT AS total FROM ({top}) GROUP BY run"


def _kinds_sql(relation: str, runs: int, m: int, w: int) -> str:
    raw = f"({0.7213 / (1 + 1.079 / m)!r}::DOUBLE * {m * m} / harmonic)"
    return (
        f"SELECT run, 'zc' AS kind, n_hat FROM ({bisect_sql(_runs_sql(relation, runs, m, w), ['run'], m, w)}) UNION ALL SELECT run, 'mr', CASE WHEN {raw} < {2.5 * m} AND empty > 0 THEN -{m}.0 * ln(empty / {m}.0) ELSE {raw} END FROM ({_ranks_sql(relation, runs, m, w)}) "
        f"UNION ALL SELECT run, 'mr_mean', {MEAN_RANK} * {m} * pow(2.0, total / {m}.0) FROM ({_ranks_sql(relation, runs, m, w)}) UNION ALL SELECT run, 'fz', pow(2.0, z / {m}.0) / {FZ_BIAS} FROM ({_fz_runs_sql(relation, runs, m, 18)})"
    )


def _fz_runs_sql(relation: str, runs: int, m: int, w: int) -> str:
    high = f"(('0x' || substr(md5('f' || run::VARCHAR || '|' || arr::VARCHAR || '|' || element), 1, 15))::BIGINT & {(1 << (w - 1)) - 1})"
    arrays = f"SELECT run, arr, bit_or(1::BIGINT << (CASE WHEN {high} = 0 THEN {w - 1} ELSE bit_count(({high} & -{high}) - 1) END)) AS bits FROM (SELECT DISTINCT element FROM ({relation})), (SELECT unnest(range({runs})) AS run), (SELECT unnest(range({m})) AS arr) GROUP BY ALL"
    return f"SELECT run, sum({low_sql('bits', w)})::BIGINT AS z FROM ({arrays}) GROUP BY run"


def hashed_fz(elements: DataFrame, n: int, runs: int, m: int, w: int) -> DataFrame:
    """``run, m, w, n, z_star`` of first-zero sketches that are really hashed: m hashes an element and run."""
    grid = elements.sparkSession.range(runs * m).select((F.col("id") / m).cast("int").alias("run"), (F.col("id") % m).cast("int").alias("arr"))
    text = F.concat_ws("|", F.concat(F.lit("f"), F.col("run").cast("string")), F.col("arr").cast("string"), "element")
    high = F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint").bitwiseAND(F.lit((1 << (w - 1)) - 1))
    rows = elements.select("element").distinct().crossJoin(F.broadcast(grid)).select("run", "arr", F.call_function("shiftleft", F.lit(1).cast("bigint"), rank_of(high, w)).alias("bit"))
    arrays = rows.groupBy("run", "arr").agg(F.bit_or("bit").alias("bits"))
    return arrays.groupBy("run").agg(F.sum(lowest_zero(F.col("bits"), w)).cast("bigint").alias("z_star")).select("run", F.lit(m).alias("m"), F.lit(w).alias("w"), F.lit(n).cast("bigint").alias("n"), "z_star")


_SMALL = fixture_sql("docs_text")


def _small_runs(s, d) -> DataFrame:
    df = fixture("docs_text", s, d)
    n = df.select("element").distinct().count()
    return estimates(hashed_states(df, n, 10, (64,), "md5", 12)).unionByName(fz_estimates(hashed_fz(df, n, 10, 64, 18)))


_SMALL_AARE = f"SELECT kind, round(avg(abs(n_hat - n) / n), 4) AS aare FROM ({_kinds_sql(_SMALL, 10, 64, 12)}), (SELECT count(DISTINCT element) AS n FROM ({_SMALL})) GROUP BY kind"


@query(_SMALL_AARE)
def acc_hashed_by_kind(s, d):
    """Errors of all sketches, every one hashed, the same hashes on both engines."""
    return measures.aare(_small_runs(s, d), ["kind"])


@query(f"WITH e AS ({_SMALL_AARE}) SELECT a.kind, round(CASE WHEN b.aare = 0 THEN NULL ELSE a.aare / b.aare END, 4) AS ratio FROM e a, e b WHERE a.kind <> 'zc' AND b.kind = 'zc'")
def acc_hashed_ratio(s, d):
    return measures.ratio_table(acc_hashed_by_kind(s, d).withColumn("all", F.lit(1)), ["all"]).select("kind", "ratio")


_NOISY_SD = 4.0
_RUN_DRAWS = f"SELECT run, sum(x)::BIGINT AS noise FROM (SELECT run, ('0x' || substr(md5('study|' || run::VARCHAR || '|' || holder), 1, 15))::BIGINT / {float(1 << 60)!r}::DOUBLE AS u FROM (SELECT DISTINCT holder FROM ({_SMALL})), (SELECT unnest(range(20)) AS run)) JOIN ({noise.pmf_sql(_NOISY_SD)}) ON u >= cdf_lo AND u < cdf_hi GROUP BY run"
_NOISY_STATES = f"SELECT run, z + noise AS z FROM ({_runs_sql(_SMALL, 20, 256, 12)}) JOIN ({_RUN_DRAWS}) USING (run)"


@query(f"SELECT round(avg(abs(n_hat - n) / n), 4) AS aare, round(stddev_samp(n_hat) / any_value(n), 4) AS rse FROM ({bisect_sql(_NOISY_STATES, ['run'], 256, 12)}), (SELECT count(DISTINCT element) AS n FROM ({_SMALL}))")
def acc_hashed_noisy(s, d):
    """Error under distributed noise, a draw of the discrete Gaussian for each holder and run, the same on both engines."""
    df = fixture("docs_text", s, d)
    n = df.select("element").distinct().count()
    runs = s.range(20).select(F.col("id").cast("int").alias("run"))
    draws = noise.draw(df.select("holder").distinct().crossJoin(runs), F.concat_ws("|", F.col("run").cast("string"), "holder"), "study", _NOISY_SD).groupBy("run").agg(F.sum("noise").alias("noise"))
    states = hashed_states(df, n, 20, (256,), "md5", 12).join(draws, "run")
    rows = states.select(zc_estimate(F.col("z") + F.col("noise"), 256, 12).alias("n_hat"))
    return rows.agg(F.round(F.avg(F.abs(F.col("n_hat") - n) / n), 4).alias("aare"), F.round(F.stddev_samp("n_hat") / n, 4).alias("rse"))


@query()
def accuracy_by_scale(s, d):
    """Bias, spread and error of the zero-count sketch at the study's defaults, hashed sets against the formula."""
    states = reduce(DataFrame.union, [states_of(s, n)[0] for n in SCALES]).where(F.col("m") == STUDY_M)
    out = measures.accuracy_summary(estimates(states).where("kind = 'zc'"), ["n", "m"])
    predicted = F.lit(math.log(2)) / F.sqrt(F.col("m").cast("double")) / F.sqrt(1 - F.exp(-F.col("n") / F.col("m")))
    return out.withColumn("predicted_rse", predicted)


_TAU = "coalesce((SELECT 10 * sum(exp(-2 * pi() * pi() * sigma * sigma * k / (k + 1.0))) FROM (SELECT unnest(range(1, 26)) AS k) WHERE k < {}), 0.0)"


@query(
    f"SELECT d::INT AS d, round(sigma, 6) AS sigma, round(least(a, b), 8) AS eps_d, CASE WHEN a <= b THEN 'root' ELSE 'sum' END AS branch, round(least(a1, b1), 8) AS eps_d_minus_1, round(0.5 * least(a, b) * (least(a, b) + 2 * sqrt(-2 * ln(1e-12))), 6) AS eps_bound, round(0.5 * least(a1, b1) * (least(a1, b1) + 2 * sqrt(-2 * ln(1e-12))), 6) AS eps_bound_curious, ceil(12 * sigma)::INT AS table_reach FROM ("
    f"SELECT d, sigma, sqrt(1 / (d * sigma * sigma) + t / 2) AS a, 1 / (sqrt(d) * sigma) + t AS b, sqrt(1 / ((d - 1) * sigma * sigma) + t1 / 2) AS a1, 1 / (sqrt(d - 1) * sigma) + t1 AS b1 FROM (SELECT d, sigma, {_TAU.format('d')} AS t, {_TAU.format('d - 1')} AS t1 FROM (SELECT d, 1 / (sqrt(d) * {STUDY_EPS_D}) AS sigma FROM (VALUES (5), (10), (15), (20), (25)) AS g(d))))"
)
def privacy_of_defaults(s, d):
    """Levels of the default release for the adversary and for curious holders, by number of holders."""
    rows = []
    for h in GRID_D:
        sigma = 1 / (math.sqrt(h) * STUDY_EPS_D)
        e, branch = privacy.eps_distributed(sigma, h)
        curious = privacy.eps_curious(sigma, h)
        rows.append((h, round(sigma, 6), round(e, 8), branch, round(curious, 8), round(privacy.cdp_bound(e, STUDY_DELTA), 6), round(privacy.cdp_bound(curious, STUDY_DELTA), 6), noise.reach(sigma)))
    return s.createDataFrame(rows, "d int, sigma double, eps_d double, branch string, eps_d_minus_1 double, eps_bound double, eps_bound_curious double, table_reach int")
