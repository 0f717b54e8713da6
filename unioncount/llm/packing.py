"""Best-fit packing by a configuration linear program over the length histogram.

A configuration is a multiset of piece lengths that fits a bin.  The covering program over configurations is solved
by multiplicative weights, whose pricing step is a knapsack by dynamic programming; the fractional solution is rounded
to whole multiplicities, the program is solved again for what remains, and the last pieces go best-fit into the room
that rounded bins have left, or into new ones.  The histogram has at most ``capacity``
entries whatever the size of the corpus, so the driver solves it, and the pieces are placed by a join on length and
rank.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, written

#: Words of a training sequence; the separator after a document counts as one.
CAPACITY = 2048
ROUNDS = 400
SALTS = 32
#: Share of the scarcest count that a round covers, and the rate at which weights fall.
STEP, RATE = 0.25, 0.3
#: What makes a full bin of long pieces worth more than one of short pieces, which are easier to place later.
LONGER = 0.02
#: The program is solved again for what rounding leaves, in half as many rounds each time; from a pass on, bins this full
#: are taken.
PASSES = (0.999, 0.995, 0.98, 0.95)


def length_of(text: Column) -> Column:
    """Whitespace-separated words and a separator; null and empty texts are a separator."""
    return F.coalesce(F.regexp_count(text, F.lit(r"\S+")), F.lit(0)) + 1


def best_configuration(lengths: np.ndarray, values: np.ndarray, counts: np.ndarray, capacity: int) -> tuple[dict[int, int], float]:
    """Knapsack by dynamic programming: a valuable multiset of lengths that fits, as ``{index: copies}``.

    The second result is the most that any multiset is worth, where a length may be used without end.  In the first no
    length is used more often than there are pieces of it; room that this leaves goes to the densest lengths that fit.
    """
    best = np.zeros(capacity + 1)
    took = np.full(capacity + 1, -1)
    for c in range(int(lengths[0]), capacity + 1):
        fit = int(np.searchsorted(lengths, c, side="right"))
        gain = values[:fit] + best[c - lengths[:fit]]
        i = int(gain.argmax())
        if gain[i] > best[c - 1]:
            best[c], took[c] = gain[i], i
        else:
            best[c] = best[c - 1]
    chosen: Counter = Counter()
    c, room = capacity, capacity
    while c > 0:
        i = int(took[c])
        if i < 0:
            c -= 1
            continue
        if chosen[i] < counts[i]:
            chosen[i] += 1
            room -= int(lengths[i])
        c -= int(lengths[i])
    if room >= lengths[0]:
        for i in np.argsort(-values / lengths, kind="stable"):
            k = min(int(counts[i]) - chosen[int(i)], room // int(lengths[i]))
            if k > 0:
                chosen[int(i)] += k
                room -= k * int(lengths[i])
    return dict(chosen), float(best[capacity])


def program(lengths: np.ndarray, counts: np.ndarray, capacity: int, rounds: int) -> tuple[dict[tuple, float], float]:
    """Fractional multiplicities of configurations that cover ``counts`` on average, and a lower bound of the bins.

    Multiplicative weights on the dual: a length's weight falls as the chosen configurations cover its count.  The bound
    is the best dual value seen (weights scaled so that no configuration is worth more than one bin), or the total
    length if that asks for more.
    """
    counts = counts.astype(float)
    weights = lengths / capacity
    covered = np.zeros(len(lengths))
    used: Counter = Counter()
    bound = float(np.ceil((lengths * counts).sum() / capacity - 1e-9))
    for _ in range(rounds):
        values = weights * (1 + LONGER * lengths / capacity)
        chosen, worth = best_configuration(lengths, values, counts, capacity)
        bound = max(bound, float((values * counts).sum() / worth))
        index = np.fromiter(chosen, int)
        rate = np.array([chosen[i] for i in index]) / counts[index]  # share of each count that one such bin covers
        step = STEP / rate.max()
        used[tuple(sorted(chosen.items()))] += step
        covered[index] += step * rate
        weights[index] *= np.exp(-RATE * step * rate)
    scale = float(counts @ lengths) / max(float((covered * counts) @ lengths), 1e-300)  # covers the corpus once on average
    return {c: x * scale for c, x in used.items()}, bound


def solve(histogram: dict[int, int], capacity: int, rounds: int = ROUNDS, report: dict | None = None) -> tuple[list[tuple[dict[int, int], int]], float]:
    """Whole configurations with multiplicities that hold each piece just once, and a lower bound of the bins needed.

    Multiplicities of the program are rounded to the nearest whole number that the remaining pieces allow, the fullest
    configurations first; the program of what remains follows, once for each of ``PASSES``.  ``report`` takes the share of
    the length that the program has placed.
    """
    lengths = np.array(sorted(histogram), np.int64)
    if not len(lengths):
        return [], 0.0
    left = np.array([histogram[int(x)] for x in lengths], np.int64)
    total = int(lengths @ left)
    plan: list[tuple[dict[int, int], int]] = []
    bound = None
    for i_pass, full in enumerate(PASSES):
        some = np.flatnonzero(left)
        if not len(some):
            break
        used, least = program(lengths[some], left[some], capacity, max(1, rounds >> i_pass))
        bound = least if bound is None else bound
        fill = {c: sum(int(lengths[some[i]]) * k for i, k in c) for c in used}
        for config in sorted(used, key=lambda c: (-fill[c], -used[c], c)):
            times = min(min(int(left[some[i]]) // k for i, k in config), int(used[config] + 0.5))
            if times > 0 and fill[config] >= full * capacity:
                plan.append(({int(some[i]): k for i, k in config}, times))
                for i, k in config:
                    left[some[i]] -= k * times
    if report is not None:
        report |= {"by_program": 1 - int(lengths @ left) / total, "bound": bound}
    plan = fill_room(plan, lengths, left, capacity)
    plan += best_fit_decreasing(lengths, left, capacity)
    return [({int(lengths[i]): k for i, k in config.items()}, times) for config, times in plan], bound


def fill_room(plan: list[tuple[dict[int, int], int]], lengths: np.ndarray, left: np.ndarray, capacity: int) -> list[tuple[dict[int, int], int]]:
    """Puts remaining pieces, the longest first, into the bins whose room they fit best; takes them off ``left``."""
    by_room: dict[int, list[list]] = {}
    for config, times in plan:
        by_room.setdefault(capacity - sum(int(lengths[i]) * k for i, k in config.items()), []).append([config, times])
    for i in np.flatnonzero(left)[::-1]:
        size = int(lengths[i])
        for room in sorted(r for r in by_room if r >= size):
            bins = by_room[room]
            while bins and left[i] > 0:
                config, times = bins.pop()
                now = min(times, int(left[i]))
                if now < times:
                    bins.append([config, times - now])
                by_room.setdefault(room - size, []).append([{**config, int(i): config.get(int(i), 0) + 1}, now])
                left[i] -= now
            if not left[i]:
                break
    return [(config, times) for bins in by_room.values() for config, times in bins]


def best_fit_decreasing(lengths: np.ndarray, left: np.ndarray, capacity: int) -> list[tuple[dict[int, int], int]]:
    """Fill bins with the largest remaining piece that fits, again and again; equal bins are made at one go."""
    plan = []
    left = left.copy()
    while (left > 0).any():
        config: Counter = Counter()
        room = capacity
        i = int(np.flatnonzero(left > 0)[-1])
        while i >= 0:
            i = min(i, int(np.searchsorted(lengths, room, side="right")) - 1)
            while i >= 0 and left[i] - config[i] <= 0:
                i -= 1
            if i < 0:
                break
            k = min(int(left[i]) - config[i], room // int(lengths[i]))
            config[i] += k
            room -= k * int(lengths[i])
            i -= 1
        times = min(int(left[j]) // k for j, k in config.items())
        for j, k in config.items():
            left[j] -= k * times
        plan.append((dict(config), times))
    return plan


def pack(docs: DataFrame, capacity: int = CAPACITY, rounds: int = ROUNDS, salts: int = SALTS, length: Column | None = None) -> DataFrame:
    """``bin_id, slot, doc_id, piece, start, length``: where each piece of each document goes.

    Lengths are words and a separator, or what the column ``length`` says (tokens, if ``docs`` has their counts; null
    and less than 1 count as 1).  Documents longer than a bin are cut into full bins and a rest; ``start`` is the first
    word of the piece.  Null and
    empty texts have length 1 (their separator).  Repeated rows and ids are packed as often as they occur.  Bins are
    numbered from 0; no bin holds more than ``capacity``.
    """
    spark = docs.sparkSession
    sized = docs.select("doc_id", (length_of(F.col("text")) if length is None else F.greatest(F.coalesce(length, F.lit(1)), F.lit(1)).cast("int")).alias("n"))
    cut = sized.select("doc_id", "n", F.explode(F.sequence(F.lit(0), ((F.col("n") - 1) / capacity).cast("int"))).alias("piece"))
    pieces = cut.select("doc_id", "piece", (F.col("piece") * capacity).alias("start"), F.least(F.col("n") - F.col("piece") * capacity, F.lit(capacity)).alias("length"))
    # equal lengths are ranked in salted parts, so that a frequent length is not one task's work
    pieces = written(pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(salts)).cast("int")), "pieces")
    cells = sorted(tuple(r) for r in pieces.groupBy("length", "salt").count().collect())  # at most capacity x salts
    histogram: Counter = Counter()
    offset = []
    for length, salt, n in cells:
        offset.append((length, salt, histogram[length]))
        histogram[length] += n
    plan, _ = solve(dict(histogram), capacity, rounds)
    ranges, first = [], 0
    taken: Counter = Counter()
    for config, times in plan:
        slot = 0
        for length, k in sorted(config.items(), reverse=True):
            ranges.append((length, taken[length], taken[length] + k * times, first, k, slot))
            taken[length] += k * times
            slot += k
        first += times
    before = spark.createDataFrame(offset, "length int, salt int, before bigint")
    place = spark.createDataFrame(ranges, "at int, lo bigint, hi bigint, first bigint, k int, slot int")
    order = Window.partitionBy("length", "salt").orderBy("doc_id", "piece")
    ranked = pieces.join(F.broadcast(before), ["length", "salt"]).withColumn("rank", F.row_number().over(order) - 1 + F.col("before"))
    # ranges are at most a few for each configuration; rows meet only those of their own length
    hit = ranked.join(F.broadcast(place), (F.col("length") == F.col("at")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    inside = F.col("rank") - F.col("lo")
    return hit.select((F.col("first") + F.floor(inside / F.col("k"))).cast("bigint").alias("bin_id"), (F.col("slot") + inside % F.col("k")).cast("int").alias("slot"), "doc_id", F.col("piece").cast("int").alias("piece"), F.col("start").cast("bigint").alias("start"), F.col("length").cast("int").alias("length"))


def op6_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole corpus packed into sequences of ``CAPACITY`` words: ``bin_id, slot, doc_id, piece, start, length``, as
    ``pack`` defines them for nulls, empty and long texts, repeated rows and empty tables."""
    return pack(table(spark, sf_dir, "documents"))


def stage_pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document goes; every row that comes in is placed."""
    return pack(docs)
