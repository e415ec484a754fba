"""Fingerprints of spot signatures.

Wherever one of the common words (``ANCHORS``) stands, the chain of the next ``CHAIN`` content words, every ``STRIDE``-th one,
forms a signature together with it.  In a stretch without common words every ``STRETCH``-th word takes their place.  The set of a text's signatures, as sorted 32-bit hashes, is its fingerprint; likeness is
the Jaccard resemblance of two sets.

Sets are partitioned by length (``partition``): each partition's lengths are ``1 / LEAST`` times those of the one before, so sets more than
one partition apart can't reach the threshold.  ``alike`` compares pruned: it stops as soon as the partitions, the lengths, or what is
left to compare decide.  :func:`compare_edited` does both for every row beside its exact likenesses; :func:`classes` joins a whole corpus:
sets of neighbouring partitions meet where they share one of their rarest signatures, as many as must contain a shared one.

Defined results: null texts are empty; an empty text has the empty set, as fingerprint the empty string; a text with words but
without a chain has its words as signatures; two empty sets are alike to degree 1, an empty and another one 0;
equal texts have equal fingerprints; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import json
import math
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from backtrail.llm.common import batches, durable, let, once
from backtrail.llm.components import components

STRIDE, CHAIN, STRETCH, MEMO, MOST_PARTS, LEAST = 1, 2, 12, 500_000, 50_000, 0.8
#: Signatures compared between two looks at what is left.
STEP = 256
#: Fixed common words of the four languages.
ANCHORS = frozenset(
    "the of and a in to is was it for with on as by at this that from an be are not or "
    "der die das und in den von zu mit sich des auf für ist im dem nicht ein eine als auch es "
    "le la les de des du et en un une que qui dans est pour par au sur pas ne ce il "
    "el la los las de del y en un una que se por con para es al lo como su no a o".split()
)
_WORD = re.compile(r"\w+")


class Signer:
    """Signature sets of texts; word codes are remembered within a bound."""

    def __init__(self):
        self.codes: dict[str, int] = {}

    def __call__(self, text: str) -> np.ndarray:
        """Sorted distinct 32-bit signatures of a whole text."""
        found = _WORD.findall(text.lower())
        if not found:
            return np.zeros(0, np.uint32)
        codes = self.codes
        for w in set(found).difference(codes):
            # The lowest bit tells anchors from content words.
            codes[w] = xxhash.xxh3_64_intdigest(w.encode()) & ~1 | (w in ANCHORS)
        coded = np.fromiter(map(codes.__getitem__, found), np.uint64, len(found))
        if len(codes) > MEMO:
            codes.clear()
        anchor = (coded & np.uint64(1)).astype(bool)
        content = coded[~anchor]
        place = np.arange(len(coded))
        since = place - np.maximum.accumulate(np.where(anchor, place, -1))
        spots = np.flatnonzero(anchor | (since % STRETCH == 0))
        nearest = np.cumsum(~anchor)[spots]  # content words up to a spot: the next one's place
        last = nearest + STRIDE * (CHAIN - 1)
        spots, nearest = spots[last < len(content)], nearest[last < len(content)]
        if not len(spots):
            return np.unique((coded >> np.uint64(32)).astype(np.uint32))
        mixed = np.where(anchor[spots], coded[spots], np.uint64(1))
        for k in range(CHAIN):
            mixed = (mixed ^ (mixed >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) + content[nearest + STRIDE * k]
        mixed = (mixed ^ (mixed >> np.uint64(32))) * np.uint64(0x94D049BB133111EB)
        return np.unique((mixed >> np.uint64(32)).astype(np.uint32))


def packed(signatures: np.ndarray) -> str:
    return base64.b64encode(signatures.astype("<u4").tobytes()).decode()


def unpacked(fingerprint: str) -> np.ndarray:
    return np.frombuffer(base64.b64decode(fingerprint), "<u4")


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard resemblance of two sorted sets."""
    if not len(a) and not len(b):
        return 1.0
    shared = len(np.intersect1d(a, b, assume_unique=True))
    return shared / (len(a) + len(b) - shared)


def partition(n: int, least: float = LEAST) -> int:
    """Number of the partition of sets with ``n`` signatures; the empty set's is -1."""
    return -1 if n == 0 else math.floor(math.log(n) / -math.log(least) + 1e-9)


def alike(a: np.ndarray, b: np.ndarray, least: float = LEAST) -> bool:
    """Whether two sorted sets are alike to degree ``least`` or more, comparing no more than decides it."""
    if not len(a) or not len(b):
        return len(a) == len(b)
    if abs(partition(len(a), least) - partition(len(b), least)) > 1 or min(len(a), len(b)) < least * max(len(a), len(b)) - 1e-9:
        return False
    need = math.ceil(least / (1 + least) * (len(a) + len(b)) - 1e-9)
    shared = passed = 0
    for i in range(0, len(a), STEP):
        part = a[i : i + STEP]
        upto = int(np.searchsorted(b, part[-1], side="right"))
        shared += int(np.isin(part, b[passed:upto], assume_unique=True).sum())
        passed = upto
        if shared >= need:
            return True
        if shared + min(len(a) - i - len(part), len(b) - passed) < need:
            return False
    return False


def edited(text: str, following: str) -> str:
    """The text with its last third replaced by the beginning of another one."""
    third = len(text) // 3
    return text[: len(text) - third] + following[:third]


def _fingerprinting(parts):
    for part in parts:
        signer = once("signer", Signer)
        found = [packed(signer(t or "")) for t in part.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([part.column(0), pa.array(found, pa.string())], ["id", "fingerprint"])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, fingerprint)`` of every row."""
    kind = df.schema[id_col].dataType.simpleString()
    return batches(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), _fingerprinting, f"id {kind}, fingerprint string").withColumnRenamed("id", id_col)


def in_turn(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """``(part, place, id, text)``: rows in descending order of id, cut into parts that each also end with the row after them.

    Cuts are ids at even quantiles.  The row behind a cut is sent to two parts; the first row of all also to the last part,
    as the one after its end.  ``place``: 0 own row, 1 row after the part's end.
    """
    rows = df.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    # Without any id the order is by text alone.
    wanted = min(max(4 * int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 2), MOST_PARTS)
    shares = F.from_json(F.lit(json.dumps([i / wanted for i in range(1, wanted)])), "array<double>")
    found, top = rows.agg(F.percentile_approx("id", shares, max(10_000, 20 * wanted)), F.max("id")).first()
    cuts = sorted(set(found or []) - {top})
    first = F.col("id") == F.lit(top) if top is not None else F.col("text") == F.lit(rows.agg(F.min("text")).first()[0])
    place = lambda part, kind: F.struct(part.cast("int").alias("part"), F.lit(kind).alias("place"))
    last = F.lit(len(cuts))

    def ends(found) -> Column:
        part = F.coalesce(found["below"], last)
        out = F.when(found["cut"], F.array(place(part, 0), place(part - 1, 1))).otherwise(F.array(place(part, 0)))
        return F.when(first, F.array_append(out, place(last, 2))).otherwise(out)

    # Part 0 holds the ids above the highest cut, the last part the lowest ids and nulls.
    spread = rows.select(F.explode(let(_located(cuts, df.schema[id_col].dataType.simpleString()), ends)).alias("end"), "id", "text")
    return spread.select("end.part", "end.place", "id", "text")


def _located(cuts: list, kind: str) -> Column:
    """Struct of the number of cuts at or above an id, null for a null one, and of whether it is a cut: a search in two levels."""
    width = max(1, math.isqrt(len(cuts)))
    blocks = [cuts[i : i + width] for i in range(0, len(cuts), width)]
    after = [len(cuts) - min((i + 1) * width, len(cuts)) for i in range(len(blocks))]
    constant = lambda value, of: F.from_json(F.lit(json.dumps(value)), of)
    block_of = F.size(F.filter(constant([b[-1] for b in blocks], f"array<{kind}>"), lambda m: m < F.col("id")))

    def within(at: Column) -> Column:
        own = F.get(constant(blocks, f"array<array<{kind}>>"), at)
        below = F.coalesce(F.size(F.filter(own, lambda c: c >= F.col("id"))), F.lit(0)) + F.coalesce(F.get(constant(after, "array<int>"), at), F.lit(0))
        return F.struct(F.when(F.col("id").isNotNull(), below).alias("below"), F.coalesce(F.array_contains(own, F.col("id")), F.lit(False)).alias("cut"))

    return let(block_of, within)


class _Neighbours:
    """Compares rows that come in order with the row after each."""

    def __init__(self):
        self.signer, self.part, self.open = once("signer", Signer), None, None

    def rows(self, parts, places, ids, texts):
        for part, place, i, text in zip(parts, places, ids, texts):
            if part != self.part:
                assert self.open is None or self.part is None or self.open[3]
                self.part, self.open = part, None
            own = self.signer(text)
            if self.open is not None and not self.open[3]:
                yield self.compared(text, own)
                self.open[3] = True
            if place == 0:
                self.open = [i, text, own, False]

    def compared(self, following: str, its: np.ndarray):
        i, text, own, _ = self.open
        changed = edited(text, following)
        after = self.signer(changed)
        found = likeness(own, after), likeness(own, its), partition(len(own)), alike(own, after), alike(own, its)
        return i, len(text), hashlib.sha256(changed.encode()).hexdigest(), packed(own), packed(after), *found


def _neighbouring(schema: pa.Schema):
    def run(parts):
        state = _Neighbours()
        for part in parts:
            done = list(state.rows(*(part.column(c).to_pylist() for c in ("part", "place", "id", "text"))))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*done) if done else [[]] * len(schema), schema.types)], schema=schema)
        assert state.open is None or state.open[3]

    return run


def compare_edited(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row's fingerprint beside those of its edited text and of the row after it, in descending order of id.

    ``near_*`` are exact; ``partition`` is the set's, and ``alike_*`` say whether the pruned comparison reaches ``LEAST``.  Nulls come
    last; equal ids stand by text, in one task that reads them one by one; the row after the last is the first.
    """
    from pyspark.sql.pandas.types import to_arrow_type

    kind = df.schema[id_col].dataType
    turn = in_turn(df, id_col, text_col)
    n = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = turn.repartition(n, "part").sortWithinPartitions("part", "place", F.col("id").desc_nulls_last(), "text")
    schema = pa.schema([("id", to_arrow_type(kind)), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64()), ("partition", pa.int32()), ("alike_edited", pa.bool_()), ("alike_next", pa.bool_())])
    out = batches(dealt, _neighbouring(schema), f"id {kind.simpleString()}, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, partition int, alike_edited boolean, alike_next boolean")
    return out.withColumnRenamed("id", id_col)


# --- similarity join ---------------------------------------------------------------------------------------------------


def _unpacking(parts):
    for part in parts:
        for name, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
            found = unpacked(text).astype(np.int64)
            for i in range(0, len(found), 1 << 16):
                own = found[i : i + (1 << 16)]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), name)), pa.array(own), pa.array(np.full(len(own), len(found), np.int32))], ["name", "signature", "n"])


def _comparing(least: float):
    def run(parts):
        for part in parts:
            found = [alike(unpacked(x), unpacked(y), least) for x, y in zip(part.column(2).to_pylist(), part.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1)], ["u", "v"]).filter(pa.array(found, pa.bool_()))

    return run


def links(sets: DataFrame, least: float = LEAST) -> DataFrame:
    """Links ``(u, v)`` between names of ``sets(name, fingerprint)`` that connect exactly what pairs alike to ``least`` or more connect.

    Two sets alike to degree t share one of the first n - ceil(t n) + 1 signatures of each in any common order; the order here is
    from the rarest, counted over all sets.  Only names and signatures are exploded; fingerprints join the pairs that remain.  In a
    signature's group every member is compared with the smallest and the largest; then all pairs that are not yet in one component.
    """
    if not 0 < least < 1:
        raise ValueError("the threshold is between 0 and 1")
    spread = batches(sets.filter("fingerprint <> ''").select("name", "fingerprint"), _unpacking, "name long, signature long, n int")
    counts = spread.groupBy("signature").agg(F.count("*").alias("held")).filter("held > 1")
    # A signature that one set holds alone leads nobody to it, but takes its place among the rarest.
    ranked = spread.join(counts, "signature", "left").select("name", "signature", "n", F.coalesce("held", F.lit(1)).alias("held"))
    rank = F.row_number().over(Window.partitionBy("name").orderBy("held", "signature"))
    leading = ranked.withColumn("rank", rank).filter((F.col("rank") <= F.col("n") - F.ceil(least * F.col("n") - 1e-9) + 1) & (F.col("held") > 1))
    grade = F.floor(F.log(F.col("n").cast("double")) / -math.log(least) + 1e-9).cast("int")
    members = durable(leading.select("name", "n", "signature", F.explode(F.array(grade, grade + 1)).alias("grade")))
    key = ["signature", "grade"]

    def confirmed(pairs: DataFrame) -> DataFrame:
        left, right = sets.select(F.col("name").alias("u"), F.col("fingerprint").alias("a")), sets.select(F.col("name").alias("v"), F.col("fingerprint").alias("b"))
        return durable(batches(pairs.join(left, "u").join(right, "v").select("u", "v", "a", "b"), _comparing(least), "u long, v long"))

    ends = members.groupBy(*key).agg(F.min(F.struct("name", "n")).alias("low"), F.max(F.struct("name", "n")).alias("high")).filter("low.name < high.name")
    pair = lambda a, b: F.struct(a["name"].alias("u"), b["name"].alias("v"), a["n"].alias("m"), b["n"].alias("n"))
    own = F.struct("name", "n")
    near = (F.col("u") < F.col("v")) & (F.least("m", "n") >= least * F.greatest("m", "n") - 1e-9)
    first = members.join(ends, key).select(F.explode(F.array(pair(F.col("low"), own), pair(own, F.col("high")))).alias("p")).select("p.*")
    first = durable(first.filter(near).select("u", "v").distinct())
    found = confirmed(first)
    rooted = members.join(components(found), F.col("name") == F.col("node"), "left").select(*key, "name", "n", F.coalesce("root", "name").alias("root"))
    apart = rooted.groupBy(*key).agg(F.min("root").alias("a"), F.max("root").alias("b")).filter("a < b").select(*key)
    left = durable(rooted.join(apart, key, "left_semi"))
    right = left.select(*key, F.col("name").alias("v"), F.col("n").alias("m"), F.col("root").alias("other"))
    rest = left.withColumnRenamed("name", "u").join(right, key).filter(near & (F.col("root") != F.col("other"))).select("u", "v").distinct()
    return found.unionAll(confirmed(rest.join(first, ["u", "v"], "left_anti")))


def classes(df: DataFrame, least: float = LEAST, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, partition, n_signatures, class_id)`` of every row: its class's smallest id, classes being linked by ``least`` or more.

    Empty texts, whose sets are empty, are one class; a class whose rows have no id has a null one.  Sets are told apart by a hash of 64 bits.
    """
    size = F.floor(F.length(F.unbase64("fingerprint")) / 4).cast("int")
    named = durable(fingerprints(df, id_col, text_col).select(id_col, F.xxhash64("fingerprint").alias("name"), "fingerprint", size.alias("n_signatures")))
    sets = named.groupBy("name").agg(F.min("fingerprint").alias("fingerprint"), F.min(id_col).alias("least_id"))
    of = sets.join(components(links(sets, least)), F.col("name") == F.col("node"), "left").select("name", "least_id", F.coalesce("root", "name").alias("root"))
    roots = of.groupBy("root").agg(F.min("least_id").alias("class_id"))
    grade = F.when(F.col("n_signatures") > 0, F.floor(F.log(F.col("n_signatures").cast("double")) / -math.log(least) + 1e-9)).otherwise(-1).cast("int")
    return named.join(of.join(roots, "root").select("name", "class_id"), "name").select(id_col, grade.alias("partition"), "n_signatures", "class_id")
