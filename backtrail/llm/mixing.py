"""Mixing sources to target weights along a curriculum.

Every source has a target of tokens and a weight schedule over training time from 0 to 1, linear between knots.  The integral
of the schedule, scaled to the target, is the source's cumulative demand.  A source's documents stand in an order fixed by a
hash of their ids and texts; the tokens before a copy of a document, put through the inverse of the demand, give its training position.
Copies whose tokens begin beyond the target are not taken; the second pass over a source begins where the first one ends.
Sorting by position deals the mix out in training order: ``deal`` gives the texts as they are trained on, ``account`` what each document
has of them.

Running sums are in two levels: a source's documents fall into buckets of about ``PER_BUCKET`` rows by a hash of id and text, summed
first (with map-side combining) and then within, so a source or an id that holds a third of all rows is spread like any other.
Texts are read twice: for the sums, from which sources and targets follow too, and for the rows.  Where the mix is dealt out they
travel to their places and, as often as taken, to their positions.
What is broadcast has a row per source; beyond ``BROADCAST_SOURCES`` of these it is joined by a shuffle.

Defined results: null and blank texts have size 0 and are taken with 0 tokens (``taken`` 0, no copies); a null source is a source
of its own, last in order; rows of equal id stand by text hash; repeated rows are documents of their own; an empty table gives
an empty result.
"""

from __future__ import annotations

from functools import partial

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from backtrail.llm.common import SPACE, durable, words

WEIGHTS, SHARE, EPOCHS = (3.0, 1.0, 2.0), 1.5, 2
PER_BUCKET, LEAST_BUCKETS, BROADCAST_SOURCES = 4096, 256, 10_000
#: Schedules that sources take in turn: (time, weight) knots; rising, even, falling.
SCHEDULES = (((0.0, 1.0), (1.0, 3.0)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 3.0), (0.5, 2.0), (1.0, 1.0)))


def size_of(text: Column) -> Column:
    """Words of a text."""
    return F.size(words(text)).cast("long")


def fill(sizes: np.ndarray, weights: np.ndarray, share: float, epochs: int) -> np.ndarray:
    """Targets by weight, none above ``epochs`` times its size: the level at which the sources together reach the share."""
    caps, total = epochs * sizes.astype(float), share * float(sizes.sum())
    order = np.argsort(caps / weights, kind="stable")
    targets, left, weight = np.zeros(len(sizes)), total, float(weights.sum())
    for i in order:
        targets[i] = min(caps[i], left * weights[i] / weight) if weight > 0 else 0.0
        left, weight = max(0.0, left - targets[i]), weight - float(weights[i])
    return targets


def _demand(schedule) -> tuple[list[float], list[float], list[float]]:
    """Knots' times and weights, and the share of demand before each."""
    times, weights = (list(map(float, x)) for x in zip(*schedule))
    areas = [(b - a) * (v + w) / 2 for a, b, v, w in zip(times, times[1:], weights, weights[1:])]
    total = sum(areas)
    if times[0] != 0 or times[-1] != 1 or total <= 0 or any(a <= 0 for a in areas):
        raise ValueError("a schedule runs from 0 to 1 in growing steps, with weight in each")
    return times, [w / total for w in weights], [0.0, *np.cumsum(areas) / total]


def position(share: Column, schedule) -> Column:
    """Time at which the share of demand before a token is reached: the root of a quadratic within its step."""
    times, weights, before = _demand(schedule)
    out = F.lit(1.0)
    for i in reversed(range(len(times) - 1)):
        v, slope = weights[i], (weights[i + 1] - weights[i]) / (times[i + 1] - times[i])
        rest = F.greatest(share - before[i], F.lit(0.0))
        # v t + slope t^2 / 2 = rest, in the form that stays exact for small slopes
        t = 2 * rest / (v + F.sqrt(F.greatest(F.lit(v * v) + 2 * slope * rest, F.lit(0.0))))
        out = F.when(share < before[i + 1], times[i] + t).otherwise(out)
    return F.least(out, F.lit(1.0))


def _time(schedule, begin: Column) -> Column:
    return position(begin / F.col("target"), schedule)


def source_table(sums: DataFrame, weights=WEIGHTS, share: float = SHARE, epochs: int = EPOCHS) -> list[tuple]:
    """``(source, size, target, schedule index)`` by code point, null last: one row per source, from sums of its buckets."""
    found = [tuple(r) for r in sums.groupBy("source").agg(F.sum("bucket_size")).collect()]
    found.sort(key=lambda r: (r[0] is None, str(r[0])))
    turn = np.arange(len(found))
    targets = fill(np.array([r[1] for r in found], np.int64), np.array(weights)[turn % len(weights)], share, epochs) if found else []
    return [(*r, float(t), int(i % len(SCHEDULES))) for r, t, i in zip(found, targets, turn)]


def _planned(df: DataFrame, whole: bool, weights, share: float, epochs: int, id_col: str, text_col: str, source_col: str, carry: bool) -> DataFrame:
    """Rows with their sizes, targets and positions; with ``carry`` the whole input row in ``row``, which then travels along."""
    spark = df.sparkSession
    tie = F.xxhash64(F.col(text_col))
    mark = F.xxhash64(F.lit("mix"), F.col(id_col), tie)
    buckets = max(LEAST_BUCKETS, -(-df.count() // PER_BUCKET))
    columns = [F.col(id_col).alias("id"), F.col(source_col).alias("source"), size_of(F.col(text_col)).alias("size"), tie.alias("tie"), mark.alias("mark"), F.pmod(F.shiftright(mark, 16), F.lit(buckets)).alias("bucket")]
    sums = durable(df.select(*columns).groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size")))
    sources = source_table(sums, weights, share, epochs)
    facts = spark.createDataFrame([(r[0], *r[1:]) for r in sources], "__s string, source_size long, target double, schedule int")
    facts = F.broadcast(facts) if len(sources) <= BROADCAST_SOURCES else facts
    sized = df.select(*columns, *([F.struct(*[df[c] for c in df.columns]).alias("row")] if carry else []))
    rows = sized.join(facts, F.col("source").eqNullSafe(F.col("__s"))).drop("__s")
    below = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select(F.col("source").alias("__s"), F.col("bucket").alias("__b"), F.coalesce(F.sum("bucket_size").over(below), F.lit(0)).alias("first"))
    within = Window.partitionBy("source", "bucket").orderBy("mark", "id", "tie")
    ahead = F.sum("size").over(within.rowsBetween(Window.unboundedPreceding, -1))
    placed = rows.withColumns({"ahead": F.coalesce(ahead, F.lit(0)), "turn": F.row_number().over(within)})
    placed = placed.join(starts, F.col("source").eqNullSafe(F.col("__s")) & (F.col("bucket") == F.col("__b"))).withColumn("start", F.col("first") + F.col("ahead"))
    budget = F.floor(F.col("target") + 0.5).cast("long")
    begins = F.transform(F.sequence(F.lit(0), F.lit(epochs - 1)), lambda e: F.col("start") + e * F.col("source_size"))
    fits = (lambda b: 2 * (budget - b) > F.col("size")) if whole else (lambda b: b < budget)
    copies = F.when(F.col("size") > 0, F.filter(begins, fits)).otherwise(F.array().cast("array<bigint>"))
    counted = F.transform("copies", lambda b: F.col("size") if whole else F.least(F.col("size"), budget - b))
    at = F.lit(None).cast("array<double>")
    for i, schedule in enumerate(SCHEDULES):
        times = F.transform("copies", partial(_time, schedule))
        at = F.when(F.col("schedule") == i, times).otherwise(at)
    placed = placed.withColumn("copies", copies).withColumns({"words": counted, "positions": at})
    return placed.withColumn("taken", F.aggregate("words", F.lit(0).cast("long"), lambda n, w: n + w))


def plan(df: DataFrame, whole: bool = False, weights=WEIGHTS, share: float = SHARE, epochs: int = EPOCHS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """``(id_col, source, size, source_size, target, taken, positions array<double>)`` of every row.

    ``positions`` has a training position for every copy that the mix takes.  The copy that crosses its source's target is
    cut there, so that a source takes its target to the word; with ``whole`` it is taken whole if more than half of it fits.
    """
    planned = _planned(df, whole, weights, share, epochs, id_col, text_col, source_col, False)
    return planned.select(F.col("id").alias(id_col), "source", "size", "source_size", "target", "taken", "positions")


def first_words(text: Column, n: Column) -> Column:
    """The text up to the end of its ``n``-th word, white space between words as it is."""
    pieces = F.split(F.translate(text, SPACE[1:], " " * 5), " ")
    start = F.struct(F.lit(0).cast("long").alias("words"), F.lit(0).alias("chars"))
    step = lambda s, p: F.struct((s["words"] + (p != "").cast("long")).alias("words"), (s["chars"] + F.length(p) + 1).alias("chars"))
    found = F.aggregate(pieces, start, lambda s, p: F.when(s["words"] < n, step(s, p)).otherwise(s))
    return F.substring(text, F.lit(1), found["chars"] - 1)


def _in_order(copies: DataFrame) -> DataFrame:
    return copies.repartitionByRange("position", "id").sortWithinPartitions("position", "id")


def deal(df: DataFrame, whole: bool = False, weights=WEIGHTS, share: float = SHARE, epochs: int = EPOCHS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix dealt out: a row for every copy, range-sorted by training position, with the text that is trained on.

    ``(id, source, bucket, turn, size, source_size, target, position, text)``; source, bucket and turn tell documents apart.  The copy
    that crosses its source's target ends there (``whole``: as in ``plan``).  Before them stand documents of which nothing is taken,
    with neither position nor text.
    """
    texts = df.select(id_col, text_col, source_col)
    planned = _planned(texts, whole, weights, share, epochs, id_col, text_col, source_col, True)
    spread = planned.select("id", "source", "bucket", "turn", "size", "source_size", "target", F.col("row")[text_col].alias("text"), F.explode_outer(F.arrays_zip("positions", "words")).alias("copy"))
    n = F.col("copy.words")
    text = F.when(n == F.col("size"), F.col("text")).when(n.isNotNull(), first_words(F.col("text"), n))
    return _in_order(spread.select("id", "source", "bucket", "turn", "size", "source_size", "target", F.col("copy.positions").alias("position"), text.alias("text")))


def account(dealt: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """``(id_col, size, source_size, target, taken, positions)`` of every document, counted in the texts that ``deal`` gives."""
    copies = dealt.withColumn("words", size_of(F.col("text")))
    whole = copies.groupBy("id", "source", "bucket", "turn", "size", "source_size", "target").agg(F.sum("words").alias("taken"), F.sort_array(F.collect_list("position")).alias("positions"))
    return whole.select(F.col("id").alias(id_col), "size", "source_size", "target", "taken", "positions")


def mix(df: DataFrame, weights=WEIGHTS, share: float = SHARE, epochs: int = EPOCHS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix itself: rows of ``df``, all columns, whole and as often as taken, range-sorted by training position."""
    planned = _planned(df, True, weights, share, epochs, id_col, text_col, source_col, True)
    return _in_order(planned.select("row", "id", F.explode("positions").alias("position"))).select("row.*")
