"""Continuous reach: sketches per window of event time, with bounded state.

A window's state is its arrays, whatever the number of events; OR is idempotent, so replays change nothing.  A watermark
closes windows, so that their rows are appended to a written table and their state is dropped.  Queries run over the
files of ``events`` to their end and return the finished rows, so that batch SQL can check them: the replay ends with
markers far ahead in time, which close what the last events left open.
"""

from __future__ import annotations

import time
from datetime import timedelta

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import privacy, sketches
from .hashing import bucket, hash60, hash_sql, rank
from .methods import ORACLES, QUERIES, query, z_sql, zc_sql
from .noise import draw, pmf_sql
from .params import ORACLE
from .sources import fixture_sql, load
from .storage import folder

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
c = F.col


def events(s: SparkSession, d: str, per_trigger: int | None = None) -> DataFrame:
    """The event files as a stream; event time is a UTC timestamp, as watermarks need."""
    reader = s.readStream.schema(EVENTS)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.option("recursiveFileLookup", True).option("pathGlobFilter", "*.parquet").parquet(f"{d}/events*.parquet").withColumn("ts", c("ts").cast("timestamp"))


MARKER = "end of replay"
DELAY = "1 day"


def slices(s: SparkSession, frames: list[DataFrame]) -> str:
    """A folder with one file for each frame, written one after the other: the file source reads by time of writing."""
    path = folder(s, "replay")
    for i, frame in enumerate(frames):
        if i:
            time.sleep(0.05)  # times of writing tell files apart
        frame.coalesce(1).write.mode("append").parquet(path)
    hadoop = s._jvm.org.apache.hadoop.fs.Path(path)
    files = hadoop.getFileSystem(s._jsc.hadoopConfiguration()).listStatus(hadoop)
    times = sorted(f.getModificationTime() for f in files if f.getPath().getName().endswith(".parquet"))
    if len(times) != len(frames) or len(set(times)) != len(times):
        raise RuntimeError("slices of a replay must be told apart by their times of writing")
    return path


def cut_by_time(s: SparkSession, d: str, parts: int = 3, markers: int = 1) -> str:
    """The events in ``parts`` files of equal spans of time, and ``markers`` files with one row far ahead each."""
    e = load(s, d, "events")
    lo, hi = e.agg(F.min("ts"), F.max("ts")).first()
    if lo is None:
        return slices(s, [e])
    span = (hi - lo) / parts
    edges = [lo + span * i for i in range(parts)] + [hi + timedelta(seconds=1)]
    frames = [e.where((c("ts") >= F.lit(a).cast("timestamp_ntz")) & (c("ts") < F.lit(b).cast("timestamp_ntz"))).sort("ts") for a, b in zip(edges, edges[1:])]
    ahead = [hi + timedelta(days=30 * (i + 1)) for i in range(markers)]
    frames += [s.range(1).select(*[(F.lit(x).cast("timestamp_ntz") if n == "ts" else F.lit(MARKER) if n == "event_type" else F.lit(-1 - i)).cast(t).alias(n) for n, t in e.dtypes]) for i, x in enumerate(ahead)]
    return slices(s, frames)


def stream_of(s: SparkSession, path: str, watermark: str | None = DELAY) -> DataFrame:
    """A replay as a stream of one slice a batch; event time is a UTC timestamp, as watermarks need."""
    rows = s.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(path).withColumn("ts", c("ts").cast("timestamp"))
    return rows.withWatermark("ts", watermark) if watermark else rows


def replay(s: SparkSession, d: str, watermark: str | None = DELAY) -> DataFrame:
    """The events in slices by time, so that the stream has several batches and the watermark moves."""
    return stream_of(s, cut_by_time(s, d), watermark)


def finish(stream: DataFrame, progress: list | None = None) -> DataFrame:
    """Run to the end of the input, appending to a written table, and return its rows; ``progress`` takes the reports."""
    s = stream.sparkSession
    path = folder(s, "stream-rows")
    q = stream.writeStream.format("parquet").outputMode("append").option("path", path).option("checkpointLocation", folder(s, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    if progress is not None:
        progress += q.recentProgress
    return s.read.schema(stream.schema).parquet(path)


def finish_changes(stream: DataFrame) -> DataFrame:
    """The same for changed rows (update mode): a folder for each batch, so that a batch that runs again replaces itself."""
    s = stream.sparkSession
    path = folder(s, "stream-rows")
    write = lambda batch, number: batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
    q = stream.writeStream.foreachBatch(write).outputMode("update").option("checkpointLocation", folder(s, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.schema(stream.schema).parquet(path).select(*stream.columns)


def placed(df: DataFrame) -> DataFrame:
    h = hash60(c("user_id").cast("string"), ORACLE.key)
    return df.withColumn("h", h).withColumn("arr", bucket(c("h"), ORACLE)).withColumn("bit", F.call_function("shiftleft", F.lit(1).cast("bigint"), rank(c("h"), ORACLE))).drop("h")


def window_sketch(stream: DataFrame, span: str, slide: str | None = None) -> DataFrame:
    """``start, holder, arr, bits`` of every window: the aggregate keeps one integer an array."""
    w = F.window("ts", span, slide) if slide else F.window("ts", span)
    return placed(stream).groupBy(w.alias("w"), c("event_type").alias("holder"), "arr").agg(F.bit_or("bit").alias("bits")).select(c("w.start").cast("timestamp_ntz").alias("start"), "holder", "arr", "bits")


_TUMBLE = "SELECT time_bucket(INTERVAL '1 day', ts)::TIMESTAMP AS start, event_type AS holder, user_id::VARCHAR AS element FROM events"


def window_zeros(rows: DataFrame) -> DataFrame:
    return sketches.zero_total(rows.where(c("holder") != MARKER), ORACLE, ("start", "holder"))


@query(z_sql(zc_sql(_TUMBLE, ORACLE, "start, holder"), ORACLE, "start, holder"))
def stream_tumbling_reach(s, d):
    return window_zeros(finish(window_sketch(replay(s, d), "1 day")))


_SLIDE = "SELECT start, event_type AS holder, user_id::VARCHAR AS element FROM (SELECT *, unnest([time_bucket(INTERVAL '1 day', ts), time_bucket(INTERVAL '1 day', ts) - INTERVAL '1 day'])::TIMESTAMP AS start FROM events)"


@query(z_sql(zc_sql(_SLIDE, ORACLE, "start, holder"), ORACLE, "start, holder"))
def stream_sliding_reach(s, d):
    return window_zeros(finish(window_sketch(replay(s, d), "2 days", "1 day")))


@query(
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS grp FROM (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))) GROUP BY user_id, grp"
)
def stream_session_reach(s, d):
    w = F.session_window("ts", "6 hours")
    rows = replay(s, d).groupBy("user_id", w.alias("w")).agg(F.count("*").alias("n"))
    return finish(rows.select("user_id", c("w.start").cast("timestamp_ntz").alias("start"), "n")).where("user_id >= 0")


def _late(s: SparkSession, d: str, progress: list) -> DataFrame:
    """Every event twice and the first hundred once more long after."""
    e = load(s, d, "events")
    # a watermark tells late rows one batch after it moves state out, hence the slice between
    path = slices(s, [e.union(e), e.orderBy(F.desc("ts"), "event_id").limit(1), e.orderBy("ts", "event_id").limit(100)])
    once = stream_of(s, path, "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return finish(once.select("event_id"), progress)


@query("SELECT count(*) AS n FROM (SELECT DISTINCT event_id FROM events)")
def stream_late(s, d):
    """Duplicates within the watermark are dropped, as are late copies."""
    return _late(s, d, []).agg(F.count("*").alias("n"))


@query("SELECT least(100, count(*))::BIGINT AS late, least(1, count(*)) + count(*) AS repeated FROM events")
def stream_dropped_rows(s, d):
    """How many rows the watermark and the search for duplicates dropped, from the reports of the run."""
    reports: list = []
    _late(s, d, reports)
    states = [x for r in reports for x in r.stateOperators]
    late = sum(x.numRowsDroppedByWatermark for x in states)
    return s.createDataFrame([(late, sum(x.customMetrics.get("numDroppedDuplicateRows", 0) for x in states))], "late bigint, repeated bigint")


@query("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(s, d):
    return finish(events(s, d).join(load(s, d, "customer"), c("user_id") == c("c_custkey")).select("event_id", "c_mktsegment"))


@query("SELECT a.event_id AS buy, b.event_id AS click FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 3 HOUR AND a.ts WHERE a.event_type = 'purchase' AND b.event_type = 'click'")
def stream_stream_join(s, d):
    """Clicks up to three hours before a purchase; the bounds let both states be dropped."""
    path = cut_by_time(s, d)  # both sides read the same slices in the same order
    buys = stream_of(s, path, None).where("event_type = 'purchase'").select(c("event_id").alias("buy"), c("user_id").alias("bu"), c("ts").alias("bt")).withWatermark("bt", DELAY)
    clicks = stream_of(s, path, None).where("event_type = 'click'").select(c("event_id").alias("click"), c("user_id").alias("cu"), c("ts").alias("ct")).withWatermark("ct", DELAY)
    return finish(buys.join(clicks, (c("bu") == c("cu")) & (c("ct") <= c("bt")) & (c("ct") >= c("bt") - F.expr("INTERVAL 3 HOURS"))).select("buy", "click"))


def stateful_sketch(stream: DataFrame, batch: bool = False) -> DataFrame:
    """Cumulative sketch of each holder in keyed state: ``holder, arr, bits`` of the arrays that a batch changed."""

    def step(key, frames, state):
        held = dict(zip(*state.get)) if state.exists else {}
        changed = set()
        for pdf in frames:
            for arr, bit in zip(pdf["arr"].tolist(), pdf["bit"].tolist()):
                now = held.get(arr, 0) | bit
                if now != held.get(arr, 0):
                    held[arr] = now
                    changed.add(arr)
        state.update(([*held], [*held.values()]))
        yield pd.DataFrame({"holder": key[0], "arr": pd.Series(sorted(changed), dtype="int32"), "bits": pd.Series([held[a] for a in sorted(changed)], dtype="int64")})

    keyed = placed(stream).select(c("event_type").alias("holder"), "arr", "bit").groupBy("holder")
    return keyed.applyInPandasWithState(step, "holder string, arr int, bits bigint", "arrs array<int>, bits array<bigint>", "update", "NoTimeout")


@query(zc_sql(fixture_sql("reach"), ORACLE))
def stream_stateful_sketch(s, d):
    rows = finish_changes(stateful_sketch(replay(s, d, None))).where(c("holder") != MARKER)
    return rows.groupBy("holder", "arr").agg(F.bit_or("bits").alias("bits"))


@query(zc_sql(fixture_sql("reach"), ORACLE))
def stream_merge_table(s, d):
    """Each batch's sketch is merged into a table of its own version: at-least-once delivery is harmless under OR."""
    path = folder(s, "table")
    schema = "holder string, arr int, bits bigint"
    state = {"version": -1}

    def merge(batch: DataFrame, number: int) -> None:
        new = placed(batch.where(c("event_type") != MARKER)).groupBy(c("event_type").alias("holder"), "arr").agg(F.bit_or("bit").alias("bits"))
        if state["version"] >= 0:
            new = new.union(s.read.schema(schema).parquet(f"{path}/v{state['version']}"))
        new.groupBy("holder", "arr").agg(F.bit_or("bits").alias("bits")).write.mode("overwrite").parquet(f"{path}/v{number}")
        state["version"] = number

    q = replay(s, d, None).writeStream.foreachBatch(merge).option("checkpointLocation", folder(s, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.schema(schema).parquet(f"{path}/v{state['version']}")


@query(z_sql(zc_sql(_TUMBLE, ORACLE, "start"), ORACLE, "start"))
def stream_daily_union(s, d):
    """Zeros of each day's union: the sketches of its holders are merged by OR."""
    merged = sketches.merge(finish(window_sketch(replay(s, d), "1 day")).where(c("holder") != MARKER), ("start",))
    return sketches.zero_total(merged, ORACLE, ("start",))


_IDLE = timedelta(hours=6)


def idle_state(stream: DataFrame) -> DataFrame:
    """``user_id, start, n``: events of each user between pauses of six hours, in keyed state that expires.

    A user's state is dropped, and its row sent, once the watermark is six hours past the user's last event.
    """

    def step(key, frames, state):
        rows = []
        if state.hasTimedOut:
            start, last, n = state.get
            rows.append((key[0], start, n))
            state.remove()
        else:
            start, last, n = state.get if state.exists else (None, None, 0)
            for t in sorted(t for pdf in frames for t in pdf["ts"].tolist()):
                if n and t >= last + _IDLE:
                    rows.append((key[0], start, n))
                    n = 0
                start, last, n = (start, t, n + 1) if n else (t, t, 1)
            state.update((start, last, n))
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, int(pd.Timestamp(last).tz_localize("UTC").timestamp() * 1000) + int(_IDLE.total_seconds() * 1000)))
        if rows:
            yield pd.DataFrame(rows, columns=["user_id", "start", "n"]).astype({"user_id": "int64", "start": "datetime64[us]", "n": "int64"})

    keyed = stream.select("user_id", "ts").groupBy("user_id")
    return keyed.applyInPandasWithState(step, "user_id bigint, start timestamp, n bigint", "start timestamp, last timestamp, n bigint", "append", "EventTimeTimeout")


@query(ORACLES["stream_session_reach"])
def stream_expiring_state(s, d):
    rows = finish(idle_state(replay(s, d))).where("user_id >= 0")
    return rows.select("user_id", c("start").cast("timestamp_ntz").alias("start"), "n")


_DAY_ZEROS = z_sql(zc_sql(_TUMBLE, ORACLE, "start"), ORACLE, "start")
_DAY_SIGMA = 4.0


@query(
    f"SELECT start, z + x AS z_noisy, round(0.5 * e * (e + 2 * sqrt(-2 * ln(1e-12))), 6) AS eps_total FROM (SELECT start, z, {hash_sql('start::VARCHAR', 'stream')} / {float(1 << 60)!r}::DOUBLE AS u, sqrt(count(*) OVER ()) / {_DAY_SIGMA} AS e FROM ({_DAY_ZEROS})) JOIN ({pmf_sql(_DAY_SIGMA)}) ON u >= cdf_lo AND u < cdf_hi"
)
def stream_private_reach(s, d):
    """A noisy release of the zeros of each day's union (``stream_daily_union``), each charged to a ledger; days are
    disjoint in time but not in users, so they add up."""
    z = stream_daily_union(s, d)
    days = z.count()
    ledger = privacy.PrivacyLedger(limit=days * 0.5 / _DAY_SIGMA**2)
    for i in range(days):
        ledger.charge(f"day {i}", 1 / _DAY_SIGMA)
    noisy = draw(z, c("start").cast("string"), "stream", _DAY_SIGMA)
    return noisy.select("start", (c("z") + c("noise")).alias("z_noisy"), F.lit(round(ledger.level(1e-12, "bound"), 6)).alias("eps_total"))


STREAMS = [k for k in QUERIES if k.startswith("stream_")]
