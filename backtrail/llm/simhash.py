"""SimHash near-duplicates by anchor-point covering.

A fingerprint has 64 bits: one where over half of the text's shingle hashes have it.  Two fingerprints link at ``THRESHOLD``
(2) or fewer differing bits.

Anchors are the words of the Hamming code over the lowest 63 bits.  It is perfect with covering radius 1: each point has one
anchor at distance 0 or 1.  Two linked fingerprints have a point half way, at most one bit from either, and that point's
anchor is within 1 + 1 bits of both.  So it is enough to send every fingerprint to all anchors within two bits, half the
threshold beyond the covering radius, when both sides of a pair are sent: at most 32 copies (a code word: one).
All 2^57 anchors exist, so an anchor gathers close fingerprints only: 2,017 patterns of 63 bits lie within two bits of it, with the
free bit 4,034 fingerprints, however large the corpus.  That bounds every group; nothing is capped.

Only distinct fingerprints are compared.  Inside an anchor, links are found exactly and left as a star per local component,
which keeps all connections without all pairs; global components follow from the stars.

Defined results: texts without a word, null or empty, have fingerprint zero and link like any other; a text of fewer than three
words has one shingle, all of it; repeated rows stay repeated and share their component; a component whose rows have no
doc_id has a null component_id; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from backtrail.llm.common import batches, durable
from backtrail.llm.components import components

SHINGLE, SEED, THRESHOLD = 3, 42, 2
#: Shingle hashes whose bits are counted at once.
BLOCK = 1 << 16


def fingerprint(text: str | None) -> int:
    """Unsigned fingerprint of one whole text."""
    found = (text or "").encode().lower().split()  # of bytes: A-Z only, and ASCII white space only
    if not found:
        return 0
    joined, n = b" ".join(found), max(1, len(found) - SHINGLE + 1)
    ends = np.cumsum([len(w) + 1 for w in found]).tolist()
    starts, stops = [0, *ends[: n - 1]], [e - 1 for e in ends[min(SHINGLE, len(found)) - 1 :]]
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts, stops)), "<u8", n)
    ones = np.zeros(64, np.int64)
    for i in range(0, n, BLOCK):
        ones += np.unpackbits(hashes[i : i + BLOCK].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def _fingerprints(parts):
    for part in parts:
        found = np.array([fingerprint(t) for t in part.column(1).to_pylist()], np.uint64).view(np.int64)
        yield pa.RecordBatch.from_arrays([part.column(0), pa.array(found)], ["id", "fp"])


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, fp long)`` of every row."""
    kind = df.schema[id_col].dataType.simpleString()
    return batches(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), _fingerprints, f"id {kind}, fp long")


def anchors(fp: Column) -> Column:
    """All code words within two bits of the lowest 63 bits, as an array of longs; bit i - 1 holds position i of the code."""
    low = fp.bitwiseAND(F.lit((1 << 63) - 1))
    bits = F.array(*[F.lit(0 if i == 0 else 1 << (i - 1)) for i in range(64)])
    syndrome = F.lit(0)
    for j in range(6):
        mask = sum(1 << (i - 1) for i in range(1, 64) if i >> j & 1)
        syndrome = syndrome + F.bit_count(low.bitwiseAND(F.lit(mask))) % 2 * (1 << j)
    pairs = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(0 if i == 0 else 1 << (i - 1)).alias("bit")) for i in range(64)])

    def around(s: Column) -> Column:
        # Flipping positions i and i xor syndrome ends in a code word; position 0 stands for no flip.
        chosen = F.filter(pairs, lambda p: p["i"] < p["i"].bitwiseXOR(s))
        return F.transform(chosen, lambda p: low.bitwiseXOR(p["bit"]).bitwiseXOR(F.get(bits, p["i"].bitwiseXOR(s))))

    return F.when(syndrome == 0, F.array(low)).otherwise(F.element_at(F.transform(F.array(syndrome.cast("int")), around), 1))


def local_star(members: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each member but the roots with the smallest member of its component; members are sorted and distinct."""
    label, bits = np.arange(len(members)), members.view(np.uint64)
    while True:
        found = label.copy()
        for i in range(0, len(bits), 512):
            near = np.bitwise_count(bits[i : i + 512, None] ^ bits[None, :]) <= THRESHOLD
            found[i : i + 512] = np.where(near, label[None, :], len(bits)).min(1)
        found = found[found]
        if (found == label).all():
            break
        label = found
    moved = label != np.arange(len(members))
    return members[moved], members[label[moved]]


def _stars(parts):
    for part in parts:
        lists = part.column(0)
        offsets, flat = np.asarray(lists.offsets), np.asarray(lists.values)
        sizes = np.diff(offsets)
        at = offsets[:-1][sizes == 2]
        a, b = flat[at], flat[at + 1]
        near = np.bitwise_count(a.view(np.uint64) ^ b.view(np.uint64)) <= THRESHOLD
        us, vs = [a[near]], [b[near]]
        for begin, size in zip(offsets[:-1][sizes > 2], sizes[sizes > 2]):
            u, v = local_star(np.sort(flat[begin : begin + size]))
            us.append(u)
            vs.append(v)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(us)), pa.array(np.concatenate(vs))], ["u", "v"])


def links(distinct: DataFrame) -> DataFrame:
    """Links ``(u, v)`` between distinct fingerprints ``fp`` that connect exactly what links at the threshold."""
    # Few bytes become 32 times as many: dealt over all tasks first, since their size alone would ask for few.
    tasks = max(1, int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    placed = distinct.repartition(tasks, "fp").select("fp", F.explode(anchors(F.col("fp"))).alias("anchor"))
    groups = placed.groupBy("anchor").agg(F.collect_set("fp").alias("fps")).filter(F.size("fps") > 1).select("fps")
    return batches(groups, _stars, "u long, v long").distinct()


def near_duplicates(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, fingerprint, component_id)`` of every row; the component's id is the smallest id reachable."""
    rows = durable(fingerprints(df, id_col, text_col))
    distinct = rows.groupBy("fp").agg(F.min("id").alias("least"))
    joined = components(links(distinct.select("fp")))
    classes = distinct.join(joined, distinct["fp"] == joined["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = classes.groupBy("root").agg(F.min("least").alias("component_id"))
    of = classes.join(named, "root").select("fp", "component_id")
    text = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return rows.join(of, "fp").select(F.col("id").alias(id_col), text.alias("fingerprint"), "component_id")

