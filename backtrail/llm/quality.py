"""Quality rules: importance of hashed n-grams, next to plain base rules.  DataFrame functions only.

Words and pairs of adjacent words fall into ``BUCKETS`` hash buckets.  Two smoothed multinomials over the buckets are counted:
of the raw corpus, from every text, and of a trusted target, from texts labelled good.  A text's score is the sum over its
n-grams of log(target / raw), divided by their number.  Bucket weights are integers (2^-20 units), so sums do not depend on
their order.  A text is kept when its score reaches the threshold: the value that best separates the labelled sample, where
losing a good text counts ``GOOD_WEIGHT`` times keeping a bad one (of equal values the smallest, which keeps more).

Labelled texts are scored for this by the target counts of the other folds of the sample: their own n-grams would flatter them.

The labelled sample is bounded: the ``SAMPLE`` labels of smallest id hash; corpus counts cover all texts.  Only the sample's ids
and the bucket table, both of fixed size, are broadcast.  Scoring has no shuffle.

Defined results: a null text has no words; a text without words fails the base rules; so does one below ``MIN_WORDS`` words or
above ``REPEAT_PERCENT`` per cent of repeated words; without labels of both kinds the threshold is open and the base rules decide
alone; equal rows get equal rows; other columns are not read (``keep`` returns all of them).
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from backtrail.llm.common import SPACE, let, words

BUCKETS, SAMPLE, SMOOTH, UNIT, GOOD_WEIGHT, FOLDS = 16_384, 20_000, 1.0, 1 << 20, 4.0, 4
WINDOW, MIN_WORDS, REPEAT_PERCENT = 5, 10, 20
SYMBOLS = "#*$%&|<>"


def _codes(found: Column) -> Column:
    """A 64-bit hash of every word."""
    return F.transform(found, lambda w: F.xxhash64(w))


def _pairs(codes: Column) -> Column:
    """A hash of every word with the one before it; the first has none."""
    return F.transform(codes, lambda c, i: F.xxhash64(c, F.get(codes, i - 1)))


def _bucket(code: Column) -> Column:
    return F.pmod(code, F.lit(BUCKETS)).cast("int")


def _grams(codes: Column) -> Column:
    """Bucket of every word, then of every pair of adjacent words; ``codes`` is bound."""
    rest = F.greatest(F.size(codes) - 1, F.lit(0))
    return F.concat(F.transform(codes, _bucket), F.slice(F.transform(_pairs(codes), _bucket), 2, rest))


def _weight(codes: Column, pairs: Column, weights: Column) -> Column:
    """Summed weight of all n-grams; both arrays are bound."""
    first = F.aggregate(codes, F.lit(0).cast("long"), lambda s, c: s + F.get(weights, _bucket(c)))
    return F.aggregate(F.slice(pairs, 2, F.greatest(F.size(pairs) - 1, F.lit(0))), first, lambda s, c: s + F.get(weights, _bucket(c)))


def repeated_words(codes: Column, pairs: Column) -> Column:
    """Words that lie in a window of five words found twice or more; both arrays are bound.  A window is two pairs and a word."""

    def covered(windows: Column) -> Column:
        def marked(ranked: Column) -> Column:
            code = lambda i: F.get(ranked, i)["code"]
            twice = F.filter(ranked, lambda r, i: F.coalesce(r["code"] == code(i - 1), F.lit(False)) | F.coalesce(r["code"] == code(i + 1), F.lit(False)))
            return let(F.sort_array(F.transform(twice, lambda r: r["at"])), lambda at: F.aggregate(F.transform(at, lambda a, i: F.least(F.coalesce(F.get(at, i + 1) - a, F.lit(WINDOW)), F.lit(WINDOW))), F.lit(0), lambda n, x: n + x))

        ranked = F.sort_array(F.transform(windows, lambda c, i: F.struct(c.alias("code"), i.alias("at"))))
        return F.when(F.size(F.array_distinct(windows)) == F.size(windows), F.lit(0)).otherwise(let(ranked, marked))

    starts = F.slice(codes, 1, F.greatest(F.size(codes) - (WINDOW - 1), F.lit(0)))
    return let(F.transform(starts, lambda c, i: F.xxhash64(F.get(pairs, i + 1), F.get(pairs, i + 3), F.get(codes, i + 4))), covered)


def _dup_lines(text: Column) -> Column:
    lines = F.filter(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(SPACE)) != "")
    return let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x)))


def measures(text: Column, weights: Column) -> Column:
    """Struct of the base measures of a text, and of its summed weight."""
    whole = F.coalesce(text, F.lit(""))
    fields = [
        F.length(F.translate(whole, SPACE, "")).cast("long").alias("word_chars"),
        (F.length(whole) - F.length(F.translate(whole, SYMBOLS, ""))).cast("long").alias("n_symbols"),
        _dup_lines(whole).cast("long").alias("n_dup_lines"),
    ]

    def counted(codes: Column, pairs: Column, weights: Column) -> Column:
        parts = [F.size(codes).cast("long").alias("n_words"), repeated_words(codes, pairs).cast("long").alias("n_repeat_words"), _weight(codes, pairs, weights).alias("weight")]
        return F.struct(*parts)

    return F.struct(*fields, let(weights, lambda w: let(_codes(words(whole)), lambda codes: let(_pairs(codes), lambda pairs: counted(codes, pairs, w)))).alias("counted"))


def score(text: Column, weights: Column) -> Column:
    """Length-normalised log-likelihood ratio alone; null without words."""

    def scored(codes: Column, pairs: Column, weights: Column) -> Column:
        return F.when(F.size(codes) > 0, _weight(codes, pairs, weights) / (F.lit(float(UNIT)) * (2 * F.size(codes) - 1)))

    return let(weights, lambda w: let(_codes(words(F.coalesce(text, F.lit("")))), lambda codes: let(_pairs(codes), lambda pairs: scored(codes, pairs, w))))


def _sample(labels: DataFrame, id_col: str) -> DataFrame:
    """At most ``SAMPLE`` labelled ids with their label."""
    rows = labels.filter(F.col(id_col).isNotNull() & F.col("quality").isNotNull()).groupBy(F.col(id_col).alias("__labelled")).agg(F.max("quality").alias("__good"))
    rows = rows.withColumn("__fold", F.pmod(F.xxhash64(F.lit("fold"), "__labelled"), F.lit(FOLDS)).cast("int"))
    return rows.orderBy(F.xxhash64("__labelled"), "__labelled").limit(SAMPLE)


def bucket_counts(df: DataFrame, sample: DataFrame, id_col: str, text_col: str) -> tuple[list[int], list[list[int]]]:
    """N-grams in every bucket: of all texts, and of the good texts of each fold; a row per bucket comes to the driver."""
    flagged = df.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text")).join(F.broadcast(sample), F.col("__id") == F.col("__labelled"), "left")
    fold = F.when(F.col("__good") > 0, F.col("__fold"))
    grams = flagged.select(fold.alias("fold"), F.explode(let(_codes(words(F.col("__text"))), _grams)).alias("bucket"))
    raw, folds = [0] * BUCKETS, [[0] * BUCKETS for _ in range(FOLDS)]
    for bucket, n, *good in grams.groupBy("bucket").agg(F.count("*"), *[F.count_if(F.col("fold") == k) for k in range(FOLDS)]).collect():
        raw[bucket] = n
        for k, g in enumerate(good):
            folds[k][bucket] = g
    return raw, folds


def bucket_weights(raw: list[int], target: list[int]) -> list[int]:
    """Log ratio of the two smoothed multinomials in every bucket, in integer units; no target says nothing."""
    if not sum(target):
        return [0] * BUCKETS
    shift = math.log(sum(raw) + SMOOTH * BUCKETS) - math.log(sum(target) + SMOOTH * BUCKETS)
    return [round(UNIT * (math.log(t + SMOOTH) - math.log(r + SMOOTH) + shift)) for t, r in zip(target, raw)]


def best_threshold(good: list[float], bad: list[float]) -> float | None:
    """The score from which on texts are kept; None if either side is empty."""
    if not good or not bad:
        return None
    marks = sorted([(s, GOOD_WEIGHT / len(good)) for s in good] + [(s, -1 / len(bad)) for s in bad])
    best, lost, at = 0.0, 0.0, marks[0][0]
    for i, (score, share) in enumerate(marks):
        if (i == 0 or marks[i - 1][0] < score) and -lost > best + 1e-12:
            best, at = -lost, (score + marks[i - 1][0]) / 2
        lost += share
    return at


def _literal(weights: list[int]) -> Column:
    """A constant array, folded once when the query is planned."""
    return F.from_json(F.lit(str(weights)), "array<bigint>")


def _with_constant(df: DataFrame, name: str, value: list, kind: str) -> DataFrame:
    """``df`` with a constant column, as a subquery that plans name by a number.

    A literal is written out (150 kB for a bucket table) wherever it stands in a plan, each time that the driver describes the plan.
    """
    return df.withColumn(name, df.sparkSession.createDataFrame([(value,)], f"value {kind}").scalar())


class QualityRules:
    """Weights and threshold of a corpus; :meth:`verdicts` applies them to any rows."""

    def __init__(self, weights: list[int], threshold: float | None):
        self.weights, self.threshold = weights, threshold

    @classmethod
    def fit(cls, df: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> QualityRules:
        sample = _sample(labels, id_col)
        ids = df.sparkSession.createDataFrame(sample.collect(), sample.schema)
        raw, folds = bucket_counts(df, ids, id_col, text_col)
        total = [sum(counts) for counts in zip(*folds)]
        marked = df.select(F.col(id_col).alias("__id"), F.col(text_col).alias("__text")).join(F.broadcast(ids), F.col("__id") == F.col("__labelled"))
        # One row per labelled id, whatever repeats in the corpus; scored by what the other folds know.
        texts = marked.groupBy("__labelled", "__good", "__fold").agg(F.min("__text").alias("__text"))
        others = [bucket_weights(raw, [t - o for t, o in zip(total, own)]) for own in folds]
        texts = _with_constant(texts, "__weights", others, "array<array<bigint>>")
        scored = texts.select("__good", score(F.col("__text"), F.get("__weights", "__fold")).alias("score"))
        found = [(r[0], r[1]) for r in scored.filter("score is not null").collect()]
        return cls(bucket_weights(raw, total), best_threshold([s for g, s in found if g > 0], [s for g, s in found if g <= 0]))

    def score(self, text: Column) -> Column:
        """Length-normalised log-likelihood ratio; null without words.  Weights stand in the column as a literal."""
        return score(text, _literal(self.weights))

    def _weighted(self, df: DataFrame) -> DataFrame:
        return _with_constant(df, "__weights", self.weights, "array<bigint>")

    @staticmethod
    def _score(m: Column) -> Column:
        n = m["counted"]["n_words"]
        return F.when(n > 0, m["counted"]["weight"] / (F.lit(float(UNIT)) * (2 * n - 1)))

    def verdicts(self, df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """``(id_col, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, score)`` of every row."""
        measured = let(measures(F.col(text_col), F.col("__weights")), self._verdict)
        return self._weighted(df).select(F.col(id_col).alias(id_col), measured.alias("v")).select(id_col, "v.*")

    def _verdict(self, m: Column) -> Column:
        counted = m["counted"]
        failed = (counted["n_words"] < MIN_WORDS) | (100 * counted["n_repeat_words"] > REPEAT_PERCENT * counted["n_words"])
        passed = F.lit(True) if self.threshold is None else F.coalesce(self._score(m) >= self.threshold, F.lit(False))
        return F.struct(
            counted["n_words"].alias("n_words"), m["word_chars"].alias("word_chars"), m["n_symbols"].alias("n_symbols"), m["n_dup_lines"].alias("n_dup_lines"),
            counted["n_repeat_words"].alias("n_repeat_words"), failed.alias("base_failed"), (~failed & passed).alias("kept"), self._score(m).alias("score"),
        )

    def keep(self, df: DataFrame, text_col: str = "text") -> DataFrame:
        """The kept rows of ``df``, all columns."""
        return self._weighted(df).filter(let(measures(F.col(text_col), F.col("__weights")), self._verdict)["kept"]).drop("__weights")
