"""Relational operators around the sketches, on the given tables; each with its SQL."""

from __future__ import annotations


import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import field, noise, sketches
from .estimate import bisect_sql, zc_estimate
from .methods import GOODS, ORACLES, QUERIES, query, z_sql, zc_sql
from .params import ORACLE, P61, P72
from .sources import PackedSketchSource, fixture, fixture_sql, load, write_packed
from .storage import folder


def L(s: SparkSession, d: str, name: str) -> DataFrame:  # noqa: N802
    return load(s, d, name)


c, lit = F.col, F.lit

# sources and sinks


@query("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity > 45")
def scan_parquet(s, d):
    return L(s, d, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_linenumber", "l_quantity")


_NATION = T.StructType([T.StructField("n_nationkey", T.IntegerType()), T.StructField("n_name", T.StringType()), T.StructField("n_regionkey", T.IntegerType())])


def _round_trip(s: SparkSession, d: str, fmt: str) -> DataFrame:
    path = folder(s, f"nation-{fmt}")
    L(s, d, "nation").write.format(fmt).save(path)
    return s.read.format(fmt).schema(_NATION).load(path)


for _fmt in ("csv", "json", "orc"):
    query("SELECT n_nationkey, n_name, n_regionkey FROM nation", f"scan_{_fmt}")(lambda s, d, x=_fmt: _round_trip(s, d, x))


@query("SELECT n_name AS value FROM nation")
def scan_text(s, d):
    path = folder(s, "nation-text")
    L(s, d, "nation").select("n_name").write.text(path)
    return s.read.text(path)


@query(zc_sql(fixture_sql("docs_text"), ORACLE))
def sink_roundtrip(s, d):
    """Sketches written as Parquet by holder and read again."""
    path = folder(s, "sketches")
    sketches.zc_sketch(fixture("docs_text", s, d), ORACLE).write.partitionBy("holder").parquet(path)
    return s.read.schema("arr int, bits bigint, holder string").parquet(path).select("holder", "arr", "bits")


@query("SELECT holder, count(*) AS n FROM (" + fixture_sql("goods") + ") WHERE holder = '3' GROUP BY holder")
def layout_by_holder(s, d):
    """A layout in which a scan meets one holder: the filter prunes folders."""
    path = folder(s, "layout")
    fixture("goods", s, d).write.partitionBy("holder").parquet(path)
    return s.read.schema("element string, holder string").parquet(path).where("holder = '3'").groupBy("holder").agg(F.count("*").alias("n"))


@query(zc_sql(fixture_sql("reach"), ORACLE))
def scan_sketch_source(s, d):
    """Packed sketches exchanged as files, read by a data source of their own."""
    path = folder(s, "packed")
    where = path if "://" in path else "file://" + path.removeprefix("file:")
    packed = sketches.pack(sketches.zc_sketch(fixture("reach", s, d), ORACLE), ORACLE)
    packed.mapInPandas(lambda batches: write_packed(batches, where), "n bigint").agg(F.sum("n")).collect()
    s.dataSource.register(PackedSketchSource)
    return s.read.format("packed_sketch").option("path", where).load()


# projections and filters


@query("SELECT o_orderkey, o_orderpriority AS holder, o_custkey::VARCHAR AS element, o_totalprice * 2 AS twice, length(o_orderstatus)::INT AS n FROM orders")
def proj_elements(s, d):
    return L(s, d, "orders").select("o_orderkey", c("o_orderpriority").alias("holder"), c("o_custkey").cast("string").alias("element"), (c("o_totalprice") * 2).alias("twice"), F.length("o_orderstatus").alias("n"))


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1996-03-01'")
def filt_range_dates(s, d):
    return L(s, d, "lineitem").where((c("l_shipdate") >= lit("1996-01-01").cast("timestamp_ntz")) & (c("l_shipdate") < lit("1996-03-01").cast("timestamp_ntz"))).select("l_orderkey", "l_linenumber")


@query("SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND NOT (o_orderstatus = 'O')")
def filt_in(s, d):
    return L(s, d, "orders").where(c("o_orderpriority").isin("1-URGENT", "2-HIGH") & ~(c("o_orderstatus") == "O")).select("o_orderkey")


@query("SELECT p_partkey, p_type FROM part WHERE p_type LIKE '%E%' AND regexp_matches(p_brand, '[135]$')")
def filt_like(s, d):
    return L(s, d, "part").where(c("p_type").like("%E%") & c("p_brand").rlike("[135]$")).select("p_partkey", "p_type")


@query("SELECT count(*) FILTER (x IS NOT DISTINCT FROM y) AS same, count(*) FILTER (x = y) AS equal, count(*) FILTER (x IS NULL) AS nulls FROM (SELECT nullif(n_regionkey, 0) AS x, nullif(n_nationkey % 5, 0) AS y FROM nation)")
def filt_nullsafe(s, d):
    t = L(s, d, "nation").select(F.nullif(c("n_regionkey"), lit(0)).alias("x"), F.nullif(c("n_nationkey") % 5, lit(0)).alias("y"))
    return t.agg(F.count_if(c("x").eqNullSafe(c("y"))).alias("same"), F.count_if(c("x") == c("y")).alias("equal"), F.count_if(c("x").isNull()).alias("nulls"))


# joins


def _orders_customer(s, d, hint):
    return L(s, d, "orders").join(L(s, d, "customer").hint(hint), c("o_custkey") == c("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


_OC = "SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"
query(_OC, "join_orders_customer")(lambda s, d: _orders_customer(s, d, "shuffle_hash"))
query(_OC, "join_orders_customer_merge")(lambda s, d: _orders_customer(s, d, "merge"))


@query("SELECT r_name, n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def join_broadcast_nation(s, d):
    """``nation`` and ``region`` have a fixed size."""
    small = F.broadcast(L(s, d, "nation").join(F.broadcast(L(s, d, "region")), c("n_regionkey") == c("r_regionkey")))
    return L(s, d, "supplier").join(small, c("s_nationkey") == c("n_nationkey")).groupBy("r_name", "n_name").agg(F.count("*").alias("n"))


_SK = zc_sql(fixture_sql("reach"), ORACLE)


@query(f"SELECT coalesce(a.arr, b.arr) AS arr, coalesce(a.bits, 0)::BIGINT AS click, coalesce(b.bits, 0)::BIGINT AS others FROM (SELECT arr, bits FROM ({_SK}) WHERE holder = 'click') a FULL JOIN (SELECT arr, bit_or(bits) AS bits FROM ({_SK}) WHERE holder <> 'click' GROUP BY arr) b ON a.arr = b.arr")
def join_full_arrays(s, d):
    """Arrays of one holder next to those of all others; absent ones are 0."""
    sk = sketches.zc_sketch(fixture("reach", s, d), ORACLE)
    a = sk.where("holder = 'click'").select("arr", c("bits").alias("x"))
    b = sk.where("holder <> 'click'").groupBy("arr").agg(F.bit_or("bits").alias("y"))
    zero = lit(0).cast("bigint")
    return a.join(b, "arr", "full").select("arr", F.coalesce("x", zero).alias("click"), F.coalesce("y", zero).alias("others"))


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def join_semi_active(s, d):
    return L(s, d, "customer").join(L(s, d, "orders").where("o_totalprice > 300000"), c("o_custkey") == c("c_custkey"), "left_semi").select("c_custkey")


@query("SELECT DISTINCT text FROM documents a WHERE source = 'src0' AND NOT EXISTS (SELECT 1 FROM documents b WHERE b.source <> 'src0' AND b.text = a.text)")
def join_anti_unseen(s, d):
    docs = L(s, d, "documents")
    return docs.where("source = 'src0'").select("text").distinct().join(docs.where("source <> 'src0'").select("text"), "text", "left_anti")


@query("WITH p AS (SELECT x, pow(2.0, -least(x + 1, 11)) / 64 AS p FROM (SELECT unnest(range(12))::INT AS x)) SELECT a.x, b.x AS y, round(pow(1 - a.p - b.p, 500), 8) AS both FROM p a JOIN p b ON a.x < b.x")
def join_theta_pairs(s, d):
    p = s.range(12).select(c("id").cast("int").alias("x"), (F.pow(lit(2.0), -F.least(c("id") + 1, lit(11))) / 64).alias("p"))
    q = p.toDF("y", "q")
    return p.join(q, c("x") < c("y")).select("x", "y", F.round(F.pow(1 - c("p") - c("q"), lit(500)), 8).alias("both"))


@query("SELECT ord.o_orderkey, b.band FROM orders ord JOIN (VALUES (0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 1e12)) AS b(band, lo, hi) ON o_totalprice >= lo AND o_totalprice < hi")
def join_cdf_range(s, d):
    """Range join of values with the cells of a small table."""
    bands = s.createDataFrame([(0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 1e12)], "band int, lo double, hi double")
    return L(s, d, "orders").join(F.broadcast(bands), (c("o_totalprice") >= c("lo")) & (c("o_totalprice") < c("hi"))).select("o_orderkey", "band")


@query("SELECT a.event_id, max(b.event_id) AS before_id FROM events a ASOF LEFT JOIN (SELECT user_id, ts, event_id FROM events WHERE event_type = 'click') b ON a.user_id = b.user_id AND a.ts > b.ts WHERE a.event_type = 'purchase' GROUP BY 1")
def join_asof_events(s, d):
    """The last click of the user before each purchase: one pass over each user's events in time order."""
    e = L(s, d, "events").where("event_type in ('click', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    micro = e.withColumn("ts", F.unix_micros(c("ts").cast("timestamp")))
    before = F.last(F.when(c("event_type") == "click", c("event_id")), ignorenulls=True).over(w)
    return micro.withColumn("before_id", before).where("event_type = 'purchase'").select("event_id", "before_id")


@query("SELECT a.event_id, count(b.event_id) AS views FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_type = 'view' AND b.ts BETWEEN a.ts - INTERVAL 6 HOUR AND a.ts WHERE a.event_type = 'purchase' GROUP BY 1")
def join_interval_events(s, d):
    """Views within six hours before each purchase: joined on user and six-hour slot, each purchase in two slots."""
    e = L(s, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(c("ts").cast("timestamp")).alias("t"))
    span = 6 * 3600 * 1_000_000
    slot = F.floor(c("t") / span)
    buys = e.where("event_type = 'purchase'").withColumn("slot", F.explode(F.array(slot, slot - 1)))
    views = e.where("event_type = 'view'").select(c("user_id").alias("u"), c("t").alias("vt"), slot.alias("vs"))
    hit = buys.join(views, (c("user_id") == c("u")) & (c("slot") == c("vs")) & (c("vt") <= c("t")) & (c("vt") >= c("t") - span), "left")
    return hit.groupBy("event_id").agg(F.count("vt").alias("views"))


@query("SELECT a.holder AS x, b.holder AS y, count(*) AS shared FROM (SELECT DISTINCT holder, element FROM (" + fixture_sql("reach") + ")) a JOIN (SELECT DISTINCT holder, element FROM (" + fixture_sql("reach") + ")) b ON a.element = b.element AND a.holder < b.holder GROUP BY ALL")
def overlap_matrix(s, d):
    a = fixture("reach", s, d).distinct()
    return a.toDF("x", "element").join(a.toDF("y", "element"), "element").where("x < y").groupBy("x", "y").agg(F.count("*").alias("shared"))


# aggregates


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem GROUP BY ALL")
def agg_basic(s, d):
    return L(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"))


@query("SELECT event_type, bit_or(user_id) AS o, bit_and(user_id) AS a, bit_xor(user_id) AS x FROM events GROUP BY 1")
def agg_bitor(s, d):
    return L(s, d, "events").groupBy("event_type").agg(F.bit_or("user_id").alias("o"), F.bit_and("user_id").alias("a"), F.bit_xor("user_id").alias("x"))


@query("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names, list(n_nationkey ORDER BY n_nationkey) AS keys FROM nation GROUP BY 1")
def agg_sorted_list(s, d):
    return L(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"), F.array_sort(F.collect_list("n_nationkey")).alias("keys"))


@query("SELECT count(DISTINCT l_orderkey) AS n FROM lineitem")
def agg_count_distinct(s, d):
    return L(s, d, "lineitem").agg(F.count_distinct("l_orderkey").alias("n"))


@query("SELECT l_returnflag, count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_multi_distinct(s, d):
    return L(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_orderkey").alias("orders"), F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("SELECT o_orderstatus, count(*) FILTER (o_totalprice > 100000) AS big, sum(CASE WHEN o_orderpriority = '1-URGENT' THEN 1 ELSE 0 END)::BIGINT AS urgent FROM orders GROUP BY 1")
def agg_filter(s, d):
    return L(s, d, "orders").groupBy("o_orderstatus").agg(F.count_if(c("o_totalprice") > 100000).alias("big"), F.sum(F.when(c("o_orderpriority") == "1-URGENT", 1).otherwise(0)).alias("urgent"))


@query("SELECT event_type, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 6) AS vp, round(corr(value, user_id), 6) AS r, round(quantile_cont(value, 0.5), 6) AS median FROM events GROUP BY 1")
def agg_stats(s, d):
    return L(s, d, "events").groupBy("event_type").agg(F.round(F.stddev_samp("value"), 6).alias("sd"), F.round(F.var_pop("value"), 6).alias("vp"), F.round(F.corr("value", "user_id"), 6).alias("r"), F.round(F.percentile("value", 0.5), 6).alias("median"))


def sketch_cube(df: DataFrame, dims: list[str], sets: list[tuple[str, ...]]) -> DataFrame:
    """Distinct counts for grouping sets from one scan: the finest sketch is built once and merged upward."""
    fine = sketches.zc_sketch(df, GOODS, tuple(dims))
    out = None
    for keys in sets:
        z = sketches.zero_total(sketches.merge(fine, keys), GOODS, keys)
        row = z.select(*[(c(k) if k in keys else lit(None).cast("string")).alias(k) for k in dims], "z", F.round(zc_estimate(c("z"), GOODS.m, GOODS.w), 4).alias("n_hat"))
        out = row if out is None else out.union(row)
    return out


_CUBE = "SELECT l_returnflag AS flag, l_linestatus AS status, l_orderkey::VARCHAR AS element FROM lineitem"


def _cube_df(s, d):
    return L(s, d, "lineitem").select(c("l_returnflag").alias("flag"), c("l_linestatus").alias("status"), c("l_orderkey").cast("string").alias("element"))


def _sets_sql(sets: list[tuple[str, ...]]) -> str:
    parts = []
    for keys in sets:
        z = z_sql(zc_sql(_CUBE, GOODS, ", ".join(keys)), GOODS, ", ".join(keys))
        cols = ", ".join(k if k in keys else f"NULL::VARCHAR AS {k}" for k in ("flag", "status"))
        parts.append(f"SELECT {cols}, z, round(n_hat, 4) AS n_hat FROM ({bisect_sql(z, list(keys), GOODS.m, GOODS.w)})")
    return " UNION ALL ".join(parts)


for _key, _sets in (("cube_reach", [("flag", "status"), ("flag",), ("status",), ()]), ("rollup_reach", [("flag", "status"), ("flag",), ()]), ("gsets_reach", [("flag",), ("status",)])):
    query(_sets_sql(_sets), _key)(lambda s, d, x=_sets: sketch_cube(_cube_df(s, d), ["flag", "status"], x))


@query("SELECT o_orderstatus, coalesce(sum(o_totalprice) FILTER (o_orderpriority = '1-URGENT'), 0)::DOUBLE AS urgent, coalesce(sum(o_totalprice) FILTER (o_orderpriority = '2-HIGH'), 0)::DOUBLE AS high FROM orders GROUP BY 1".replace("coalesce(sum", "round(coalesce(sum").replace("0)::DOUBLE", "0)::DOUBLE, 2)"))
def pivot_error(s, d):
    p = L(s, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "2-HIGH"]).agg(F.sum("o_totalprice"))
    return p.select("o_orderstatus", F.round(F.coalesce(c("1-URGENT"), lit(0.0)), 2).alias("urgent"), F.round(F.coalesce(c("2-HIGH"), lit(0.0)), 2).alias("high"))


@query("SELECT s_suppkey, m AS measure, v AS value FROM (SELECT s_suppkey, unnest(['balance', 'double']) AS m, unnest([s_acctbal, s_acctbal * 2]) AS v FROM supplier)")
def unpivot_error(s, d):
    t = L(s, d, "supplier").select("s_suppkey", c("s_acctbal").alias("balance"), (c("s_acctbal") * 2).alias("double"))
    return t.unpivot("s_suppkey", ["balance", "double"], "measure", "value")


# windows


@query("SELECT c_custkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS rk, dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS dr, ntile(4) OVER w AS q FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_custkey)".replace("row_number() OVER w", "(row_number() OVER w)::INT").replace(" rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment)", " (rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment))::INT").replace("dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment)", "(dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment))::INT").replace("ntile(4) OVER w", "(ntile(4) OVER w)::INT"))
def win_rank(s, d):
    w, v = Window.partitionBy("c_nationkey").orderBy("c_custkey"), Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    return L(s, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("q"))


@query("SELECT s_suppkey, round(percent_rank() OVER w, 8) AS pr, round(cume_dist() OVER w, 8) AS cd FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal)")
def win_dist(s, d):
    w = Window.partitionBy("s_nationkey").orderBy("s_acctbal")
    return L(s, d, "supplier").select("s_suppkey", F.round(F.percent_rank().over(w), 8).alias("pr"), F.round(F.cume_dist().over(w), 8).alias("cd"))


@query("SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_dedup(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return L(s, d, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w).alias("second"))


_DAY = "SELECT strftime(ts, '%Y-%m-%d') AS day, user_id::VARCHAR AS element FROM events"


@query(f"WITH k AS ({zc_sql(_DAY, ORACLE, 'day')}), days AS (SELECT DISTINCT day FROM k), grid AS (SELECT day, arr FROM days, (SELECT DISTINCT arr FROM k)), run AS (SELECT day, arr, bit_or(bits) OVER (PARTITION BY arr ORDER BY day) AS bits FROM grid LEFT JOIN k USING (day, arr)) SELECT day, ({ORACLE.m * ORACLE.w} - sum(coalesce(bit_count(bits), 0)))::BIGINT AS z FROM run GROUP BY day")
def win_running_reach(s, d):
    """Growth of a campaign: running OR over days, array by array."""
    days = L(s, d, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), c("user_id").cast("string").alias("element"))
    sk = sketches.zc_sketch(days, ORACLE, ("day",))
    grid = sk.select("day").distinct().crossJoin(sk.select("arr").distinct())
    run = F.bit_or("bits").over(Window.partitionBy("arr").orderBy("day").rowsBetween(Window.unboundedPreceding, 0))
    full = grid.join(sk, ["day", "arr"], "left").withColumn("bits", run)
    return sketches.zero_total(full, ORACLE, ("day",))


@query("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS last3, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS near FROM orders")
def win_range_sum(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return L(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w.rowsBetween(-2, 0)), 2).alias("last3"), F.count("*").over(w.rangeBetween(-1000, 0)).alias("near"))


# order and limits


@query("SELECT holder, count(DISTINCT element) AS n FROM (" + fixture_sql("goods") + ") GROUP BY 1 ORDER BY n DESC, holder LIMIT 5")
def topk_holders(s, d):
    return fixture("goods", s, d).groupBy("holder").agg(F.count_distinct("element").alias("n")).orderBy(F.desc("n"), "holder").limit(5)


@query("SELECT c_nationkey, c_custkey, c_acctbal FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) <= 3")
def topk_per_group(s, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return L(s, d, "customer").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("c_nationkey", "c_custkey", "c_acctbal")


@query("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20 OFFSET 10")
def sort_limit_offset(s, d):
    return L(s, d, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").offset(10).limit(20)


# set operations


def _ab(s, d):
    o = L(s, d, "orders")
    return o.where("o_orderpriority = '1-URGENT'").select("o_custkey"), o.where("o_orderstatus = 'F'").select("o_custkey")


_A, _B = "SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT'", "SELECT o_custkey FROM orders WHERE o_orderstatus = 'F'"
query(f"{_A} UNION {_B}", "set_union")(lambda s, d: (lambda a, b: a.union(b).distinct())(*_ab(s, d)))
query(f"{_A} UNION ALL {_B}", "set_union_all")(lambda s, d: (lambda a, b: a.unionByName(b))(*_ab(s, d)))
query(f"{_A} INTERSECT {_B}", "set_intersect")(lambda s, d: (lambda a, b: a.intersect(b))(*_ab(s, d)))
query(f"{_A} EXCEPT {_B}", "set_except")(lambda s, d: (lambda a, b: a.subtract(b))(*_ab(s, d)))
query(f"{_A} INTERSECT ALL {_B}", "set_intersect_all")(lambda s, d: (lambda a, b: a.intersectAll(b))(*_ab(s, d)))
query(f"{_A} EXCEPT ALL {_B}", "set_except_all")(lambda s, d: (lambda a, b: a.exceptAll(b))(*_ab(s, d)))


def _pairs(s, d):
    sk = sketches.zc_sketch(fixture("patients", s, d), ORACLE)
    names = sk.select("holder").distinct()
    pairs = names.toDF("x").join(names.toDF("y"), c("x") < c("y"))
    both = pairs.join(sk, (c("holder") == c("x")) | (c("holder") == c("y")))
    z = sketches.zero_total(sketches.merge(both, ("x", "y")), ORACLE, ("x", "y"))
    return sk, z.select("x", "y", "z", zc_estimate(c("z"), ORACLE.m, ORACLE.w).alias("e"))


_PSK = zc_sql(fixture_sql("patients"), ORACLE)
_PAIRS = f"SELECT x, y, ({ORACLE.m * ORACLE.w} - sum(bit_count(bits)))::BIGINT AS z FROM (SELECT x, y, arr, bit_or(bits) AS bits FROM (SELECT DISTINCT holder AS x FROM ({_PSK})) a JOIN (SELECT DISTINCT holder AS y FROM ({_PSK})) b ON x < y JOIN ({_PSK}) k ON k.holder = x OR k.holder = y GROUP BY ALL) GROUP BY x, y"
_ONE = bisect_sql(z_sql(_PSK, ORACLE, "holder"), ["holder"], ORACLE.m, ORACLE.w)


@query(f"SELECT x, y, z, round(n_hat, 4) AS n_hat FROM ({bisect_sql(_PAIRS, ['x', 'y'], ORACLE.m, ORACLE.w)})")
def sketch_union_pairs(s, d):
    return _pairs(s, d)[1].select("x", "y", "z", F.round("e", 4).alias("n_hat"))


@query(f"SELECT p.x, p.y, round(a.n_hat + b.n_hat - p.n_hat, 3) AS shared_hat FROM ({bisect_sql(_PAIRS, ['x', 'y'], ORACLE.m, ORACLE.w)}) p JOIN ({_ONE}) a ON a.holder = p.x JOIN ({_ONE}) b ON b.holder = p.y")
def sketch_intersection(s, d):
    """Intersections by inclusion and exclusion of estimates."""
    sk, pairs = _pairs(s, d)
    one = sketches.zero_total(sk, ORACLE, ("holder",)).select("holder", zc_estimate(c("z"), ORACLE.m, ORACLE.w).alias("n"))
    a, b = one.toDF("x", "nx"), one.toDF("y", "ny")
    return pairs.join(a, "x").join(b, "y").select("x", "y", F.round(c("nx") + c("ny") - c("e"), 3).alias("shared_hat"))


# scalar functions


@query("SELECT n_nationkey, lower(n_name) AS lo, substring(n_name, 2, 3) AS sub, string_split(n_name, 'A')[1] AS head, concat_ws('-', n_name, n_regionkey::VARCHAR) AS cat, regexp_extract(n_name, '([A-Z])$', 1) AS last, regexp_replace(n_name, '[AEIOU]', '*', 'g') AS veiled, levenshtein(n_name, 'FRANCE')::INT AS far, lpad(n_name, 12, '.') AS pad FROM nation")
def fn_string(s, d):
    n = c("n_name")
    return L(s, d, "nation").select("n_nationkey", F.lower(n).alias("lo"), F.substring(n, 2, 3).alias("sub"), F.split(n, "A")[0].alias("head"), F.concat_ws("-", n, c("n_regionkey").cast("string")).alias("cat"), F.regexp_extract(n, "([A-Z])$", 1).alias("last"), F.regexp_replace(n, "[AEIOU]", "*").alias("veiled"), F.levenshtein(n, lit("FRANCE")).alias("far"), F.lpad(n, 12, ".").alias("pad"))


@query("SELECT r_regionkey, md5(r_name) AS m, sha256(r_name) AS s, ('0x' || substr(md5(r_name), 1, 15))::BIGINT AS h, upper(hex(r_name)) AS x, base64(r_name::BLOB) AS b FROM region")
def fn_hash(s, d):
    r = c("r_name")
    return L(s, d, "region").select("r_regionkey", F.md5(r).alias("m"), F.sha2(r, 256).alias("s"), F.conv(F.substring(F.md5(r), 1, 15), 16, 10).cast("bigint").alias("h"), F.hex(r).alias("x"), F.base64(r.cast("binary")).alias("b"))


@query(r"SELECT page_id, regexp_extract(url, '^(https?)://', 1) AS scheme, regexp_extract(url, '^https?://([^/:?#]+)', 1) AS host FROM pages")
def fn_url(s, d):
    return L(s, d, "pages").select("page_id", F.try_parse_url("url", lit("PROTOCOL")).alias("scheme"), F.try_parse_url("url", lit("HOST")).alias("host"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS month, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS days, (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE AS next, year(o_orderdate)::INT AS y, dayofweek(o_orderdate)::INT + 1 AS dow FROM orders".replace("dayofweek(o_orderdate)::INT + 1", "(dayofweek(o_orderdate) + 1)::INT"))
def fn_date(s, d):
    o = c("o_orderdate")
    return L(s, d, "orders").select("o_orderkey", F.date_trunc("month", o).cast("timestamp_ntz").alias("month"), F.datediff(o, lit("1995-01-01").cast("date")).alias("days"), F.add_months(o.cast("date"), 1).alias("next"), F.year(o).alias("y"), F.dayofweek(o).alias("dow"))


@query("SELECT l_orderkey, l_linenumber, round(exp(l_tax), 8) AS e, round(ln(1 + l_discount), 8) AS lp, round(pow(l_quantity, 1.5), 6) AS p, ((l_orderkey * 7 - 50) % 13 + 13) % 13 AS pm, greatest(l_tax, l_discount) AS g, ceil(l_extendedprice)::BIGINT AS c FROM lineitem")
def fn_math(s, d):
    return L(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.exp("l_tax"), 8).alias("e"), F.round(F.log1p("l_discount"), 8).alias("lp"), F.round(F.pow("l_quantity", lit(1.5)), 6).alias("p"), F.pmod(c("l_orderkey") * 7 - 50, lit(13)).alias("pm"), F.greatest("l_tax", "l_discount").alias("g"), F.ceil("l_extendedprice").alias("c"))


@query("SELECT b::BIGINT AS b, (b & 6)::BIGINT AS a, (b | 9)::BIGINT AS o, xor(b, 5)::BIGINT AS x, (~b)::BIGINT AS n, bit_count(b)::INT AS ones, (b << 3)::BIGINT AS l, (b >> 1)::BIGINT AS r, bit_count((~b & (b + 1)) - 1)::INT AS low FROM (SELECT unnest(range(64)) AS b)")
def fn_bits(s, d):
    b = c("id")
    return s.range(64).select(b.alias("b"), b.bitwiseAND(6).alias("a"), b.bitwiseOR(9).alias("o"), b.bitwiseXOR(5).alias("x"), F.bitwise_not(b).alias("n"), F.bit_count(b).alias("ones"), F.shiftleft(b, 3).alias("l"), F.shiftright(b, 1).alias("r"), sketches.lowest_zero(b, 60).alias("low"))


@query(f"SELECT i::BIGINT AS i, (({P61 - 1} - i * 1000003) * ({P61 - 2} - i) % {P61})::VARCHAR AS product FROM (SELECT unnest(range(100))::HUGEINT AS i)")
def fn_modmul(s, d):
    i = c("id").cast("decimal(38,0)")
    return s.range(100).select(c("id").alias("i"), field.mul((field.constant(P61 - 1) - i * 1000003).cast("decimal(38,0)"), (field.constant(P61 - 2) - i).cast("decimal(38,0)")).cast("string").alias("product"))


@query("SELECT i::BIGINT AS i, list_sum(list_transform(range(0, i + 1), lambda x: x * x))::BIGINT AS squares, len(list_filter(range(0, i + 1), lambda x: x % 3 = 0))::INT AS thirds, list_contains(range(0, i + 1), 7) AS has7, list_slice(range(0, i + 1), 2, 3) AS part FROM (SELECT unnest(range(3, 20)) AS i)")
def fn_array(s, d):
    a = F.sequence(lit(0).cast("bigint"), c("id"))
    return s.range(3, 20).select(c("id").alias("i"), F.aggregate(F.transform(a, lambda x: x * x), lit(0).cast("bigint"), lambda p, x: p + x).alias("squares"), F.size(F.filter(a, lambda x: x % 3 == 0)).alias("thirds"), F.exists(a, lambda x: x == 7).alias("has7"), F.slice(a, 2, 2).alias("part"))


@query(f"SELECT x::BIGINT AS x, ((((3 * x + 5) % {P61}) * x + 7) % {P61})::VARCHAR AS value FROM (SELECT (unnest(range(50))::HUGEINT * 46116860184273879) AS x)")
def fn_poly_eval(s, d):
    x = (c("id") * 46116860184273879).cast("decimal(38,0)")
    return s.range(50).select((c("id") * 46116860184273879).alias("x"), field.horner([7, 5, 3], x).cast("string").alias("value"))


@query("SELECT n_regionkey, count(*)::INT AS n, string_agg(upper(n_name), ',' ORDER BY n_nationkey) FILTER (n_nationkey > 5) AS names FROM nation GROUP BY 1")
def fn_map(s, d):
    m = L(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m"))
    big = F.transform_values(F.map_filter("m", lambda k, v: k > 5), lambda k, v: F.upper(v))
    ordered = F.transform(F.array_sort(F.map_keys(big)), lambda k: F.element_at(big, k))
    return m.select("n_regionkey", F.size("m").alias("n"), F.nullif(F.array_join(ordered, ","), lit("")).alias("names"))


@query("SELECT event_id, (props->>'k')::INT AS k, (props->>'k')::INT AS k2, (props->>'k')::INT AS k3 FROM events")
def fn_json(s, d):
    e = L(s, d, "events")
    return e.select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2"), F.variant_get(F.parse_json("props"), "$.k", "int").alias("k3"))


@query("SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS seg, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal > 5000 THEN 'rich' ELSE 'mid' END AS class, TRY_CAST(c_name AS INT) AS bad, CASE WHEN c_nationkey = 0 THEN NULL ELSE round(c_acctbal / c_nationkey, 6) END AS per FROM customer")
def fn_null(s, d):
    return L(s, d, "customer").select("c_custkey", F.coalesce(F.nullif(c("c_mktsegment"), lit("BUILDING")), lit("none")).alias("seg"), F.when(c("c_acctbal") < 0, "debt").when(c("c_acctbal") > 5000, "rich").otherwise("mid").alias("class"), c("c_name").try_cast("int").alias("bad"), F.round(F.try_divide("c_acctbal", "c_nationkey"), 6).alias("per"))


# SQL surface


def view(s: SparkSession, d: str, *names: str) -> None:
    for n in names:
        load(s, d, n).createOrReplaceTempView(n)


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
def sub_scalar(s, d):
    view(s, d, "orders")
    return s.sql("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")


_EXISTS = "SELECT s_suppkey FROM supplier WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_suppkey = s_suppkey AND l_quantity > 49) AND s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey < 3)"


@query(_EXISTS)
def sub_exists(s, d):
    view(s, d, "supplier", "lineitem", "nation")
    return s.sql(_EXISTS)


@query("SELECT n_name, c_custkey FROM nation JOIN (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) ON c_nationkey = n_nationkey WHERE r <= 2")
def lateral_topn(s, d):
    view(s, d, "nation", "customer")
    return s.sql("SELECT n_name, t.c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) t")


def register_sql(s: SparkSession, m: int = GOODS.m, w: int = GOODS.w, key: str = GOODS.key) -> None:
    """SQL functions ``zc_bucket``, ``zc_rank`` and ``zc_estimate`` for these parameters; Catalyst inlines them."""
    from .theory import rank_probs

    r = m.bit_length() - 1
    h = f"cast(conv(substring(md5(concat('{key}|', e)), 1, 15), 16, 10) AS bigint)"
    high = f"(shiftrightunsigned({h}, {r}) & {(1 << (w - 1)) - 1})"
    probs = ", ".join(f"{-q!r}D" for q in rank_probs(m, w))
    f = f"aggregate(array({probs}), 0D, (acc, q) -> acc + exp((b.lo + b.hi) / 2 * q)) / {float(w)!r}D"
    s.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION zc_bucket(e STRING) RETURNS INT RETURN cast({h} & {m - 1} AS int)")
    s.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION zc_rank(e STRING) RETURNS INT RETURN CASE WHEN {high} = 0 THEN {w - 1} ELSE bit_count(({high} & -{high}) - 1) END")
    s.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION zc_estimate(z BIGINT) RETURNS DOUBLE RETURN CASE WHEN z >= {m * w} THEN 0D ELSE aggregate(sequence(1, 60), named_struct('lo', 0D, 'hi', {float(m * 2**w)!r}D), "
        f"(b, i) -> named_struct('lo', CASE WHEN {f} > z / {float(m * w)!r}D THEN (b.lo + b.hi) / 2 ELSE b.lo END, 'hi', CASE WHEN {f} > z / {float(m * w)!r}D THEN b.hi ELSE (b.lo + b.hi) / 2 END), b -> (b.lo + b.hi) / 2) END"
    )


@query(ORACLES["patients_by_segment"])
def sql_surface(s, d):
    register_sql(s)
    view(s, d, "orders", "customer")
    return s.sql(
        "SELECT segment, z, round(zc_estimate(z), 4) AS n_hat FROM (SELECT segment, 12288 - sum(bit_count(bits)) AS z FROM (SELECT c_mktsegment AS segment, zc_bucket(cast(o_custkey AS string)) AS arr, bit_or(shiftleft(1L, zc_rank(cast(o_custkey AS string)))) AS bits FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2) GROUP BY 1)"
    )


@query("SELECT z, round(n_hat, 4) AS n_hat FROM (" + bisect_sql("SELECT 498::BIGINT AS z", [], 64, 12) + ")")
def sql_recursive_bisect(s, d):
    """The bisection as a recursive query."""
    from .theory import rank_probs

    terms = " + ".join(f"exp((lo + hi) / 2 * {-q!r}D)" for q in rank_probs(64, 12))
    return s.sql(
        f"WITH RECURSIVE b(k, lo, hi) AS (SELECT 0, 0D, {float(64 * 2**12)!r}D UNION ALL SELECT k + 1, CASE WHEN ({terms}) / 12D > 498 / 768D THEN (lo + hi) / 2 ELSE lo END, CASE WHEN ({terms}) / 12D > 498 / 768D THEN hi ELSE (lo + hi) / 2 END FROM b WHERE k < 60) "
        "SELECT cast(498 AS bigint) AS z, round((lo + hi) / 2, 4) AS n_hat FROM b WHERE k = 60"
    )


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE ('0x' || substr(md5('sample|' || l_orderkey::VARCHAR), 1, 15))::BIGINT % 10 = 0")
def sample_hash(s, d):
    """A tenth of the orders with all their lines, the same on every run."""
    from .hashing import hash60

    return L(s, d, "lineitem").where(hash60(c("l_orderkey").cast("string"), "sample") % 10 == 0).select("l_orderkey", "l_linenumber")


QUERIES["sample_rows"] = lambda s, d: L(s, d, "orders").sampleBy("o_orderstatus", {"F": 0.2, "O": 0.1}, seed=3).select("o_orderkey", "o_orderstatus")

# Python at the edges


@query("SELECT holder, z FROM (" + z_sql(zc_sql(fixture_sql("reach"), ORACLE), ORACLE, "holder") + ")")
def udaf_dense_sketch(s, d):
    """The whole sketch as one grouped aggregate in Python, to compare with the native one."""
    import numpy as np

    from .hashing import bucket, hash60, rank

    m, w = ORACLE.m, ORACLE.w

    @F.pandas_udf("bigint")
    def zeros(arr: pd.Series, x: pd.Series) -> int:
        cells = np.zeros((m, w), bool)
        cells[arr.to_numpy(), x.to_numpy()] = True
        return int(m * w - cells.sum())

    h = hash60(c("element"), ORACLE.key)
    return fixture("reach", s, d).select("holder", bucket(h, ORACLE).alias("arr"), rank(h, ORACLE).alias("x")).groupBy("holder").agg(zeros("arr", "x").alias("z"))


@query(zc_sql(fixture_sql("goods"), ORACLE))
def map_dense(s, d):
    """Partition-local merge in Arrow before the exchange: one row for each array that a partition touches."""
    import numpy as np
    import pyarrow as pa

    from .hashing import bucket, hash60, rank

    m, w = ORACLE.m, ORACLE.w

    def local(batches):
        held = {}
        for b in batches:
            arr, x = b.column("arr").to_numpy(), b.column("x").to_numpy()
            holders = b.column("holder").dictionary_encode()
            names, codes = holders.dictionary.to_pylist(), holders.indices.to_numpy()
            for i, name in enumerate(names):
                bits = held.setdefault(name, np.zeros(m, np.int64))
                mine = codes == i
                np.bitwise_or.at(bits, arr[mine], np.int64(1) << x[mine].astype(np.int64))
        for name, bits in held.items():
            at = np.flatnonzero(bits)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at)), pa.array(at.astype(np.int32)), pa.array(bits[at])], ["holder", "arr", "bits"])

    h = hash60(c("element"), ORACLE.key)
    placed = fixture("goods", s, d).select("holder", bucket(h, ORACLE).alias("arr"), rank(h, ORACLE).alias("x"))
    return sketches.merge(placed.mapInArrow(local, "holder string, arr int, bits bigint"), ("holder",)).select("holder", "arr", "bits")


@query("SELECT x::INT AS x, round(pow(2.0, -least(x + 1, 11)) / 64, 12) AS p FROM (SELECT unnest(range(12)) AS x)")
def udtf_pmf(s, d):
    from .theory import rank_probs

    @F.udtf(returnType="x int, p double")
    class Probs:
        def eval(self, m: int, w: int):
            for x, q in enumerate(rank_probs(m, w)):
                yield x, round(q, 12)

    return Probs(lit(64), lit(12))


@query("SELECT m::INT AS m, d::INT AS d, eps FROM (VALUES (1024), (2048), (4096), (8192)) AS a(m), (VALUES (5), (10), (15), (20), (25)) AS b(d), (VALUES (0.1::DOUBLE), (0.2), (0.3), (0.4), (0.5)) AS e(eps)")
def udtf_grid(s, d):
    @F.udtf(returnType="m int, d int, eps double")
    class Grid:
        def eval(self):
            for m in (1024, 2048, 4096, 8192):
                for h in (5, 10, 15, 20, 25):
                    for e in (k / 10 for k in range(1, 6)):
                        yield m, h, e

    return Grid()


_X, _Y = "(i * 48271 + 11)::HUGEINT * 68719476743", "(i * i + 40014)::HUGEINT * 33554467"


@query(f"SELECT i::BIGINT AS id, (({_X}) * ({_Y}) % {P72})::VARCHAR AS product, TRUE AS same FROM (SELECT unnest(range(500)) AS i)")
def udf_field72(s, d):
    """Products in the field of 72 bits by an Arrow UDF on whole numbers, next to the limbs of DECIMAL columns."""

    @F.pandas_udf("string")
    def times(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([str(int(x) * int(y) % P72) for x, y in zip(a, b)])

    i = c("id").cast("decimal(38,0)")
    x, y = (i * 48271 + 11) * 68719476743, (i * i + 40014) * 33554467
    rows = s.range(500).select("id", field.reduce_(x, P72).alias("x"), field.reduce_(y, P72).alias("y"))
    done = rows.select("id", times(c("x").cast("string"), c("y").cast("string")).alias("product"), field.mul(c("x"), c("y"), P72).cast("string").alias("limbs"))
    return done.select("id", "product", (c("product") == c("limbs")).alias("same"))


@query("SELECT x::INT AS x, CASE WHEN x = 1 THEN '0' ELSE '1' END AS value FROM (SELECT unnest(range(1, 7)) AS x)")
def udtf_lookup_poly(s, d):
    """Coefficients of the lookup polynomial from a table function, put to use at 1..6."""
    from .field import lookup_poly

    @F.udtf(returnType="t int, beta string")
    class Coefficients:
        def eval(self, k: int):
            for t, beta in enumerate(lookup_poly(k)):
                yield t, str(beta)

    points = s.range(1, 7).select(c("id").cast("int").alias("x"))
    dec = lambda e: e.cast("decimal(38,0)")
    term = field.mul(dec(c("beta")), dec(F.pow(c("x").cast("double"), c("t").cast("double")).cast("bigint")))
    return Coefficients(lit(5)).crossJoin(points).groupBy("x").agg(field.reduce_(F.sum(term)).cast("string").alias("value"))


@query(f"SELECT x, round(pmf, 10) AS pmf FROM ({noise.pmf_sql(3.0)})")
def udtf_gaussian(s, d):
    """The table of the discrete Gaussian from a table function."""

    @F.udtf(returnType="x bigint, pmf double")
    class Table:
        def eval(self, sigma: float):
            import math

            k = math.ceil(12 * sigma)
            weights = [math.exp(-(x * x) / (2 * sigma * sigma)) for x in range(-k, k + 1)]
            for x, v in zip(range(-k, k + 1), weights):
                yield x, round(v / sum(weights), 10)

    return Table(lit(3.0))
