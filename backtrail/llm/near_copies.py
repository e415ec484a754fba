"""SimHash near copies at a similarity: anchor-point covering on blocks of a long fingerprint, confirmed exactly.

A text is the set of its hashed runs of ``SHINGLE`` (5) lower-cased words; two texts link at Jaccard ``LEAST`` (0.8) or more.  Sets that
alike differ in about 15 per cent of their SimHash bits, far beyond what one covering of 64 bits can reach.  So the fingerprint has
``WORDS`` words of 64 bits.  ``BLOCKS`` blocks of 31 bits are each covered by the Hamming code of that length (perfect, radius 1; see
:mod:`backtrail.llm.simhash`): a block goes to all anchors within two bits, at most 16, so blocks within two bits surely meet.  The
last word stays out of the blocks: most of it goes along, and members of an anchor are compared by it.

Anchors are dealt by range of (anchor, word, number), so a heavy one is spread over tasks, and read in order.  The members of an anchor of up
to ``NEAR`` + 1 are compared at once; an anchor of more members, or one that a range border cuts, goes through a second round where its
members are not in one component yet, which is told from a row for every component of an anchor.  There members come with their sets, once an anchor, and are compared
where they meet: what leaves is a forest, fewer links than members, and no list of pairs.  An anchor too large to be read at once is dealt as
pairs of blocks.  No pair counts before the whole fingerprints and then the two whole sets are compared.

Measured on the tables (README): of pairs at 0.8 or more 0.993 meet at an anchor, of their groups more, since groups have many pairs.

Defined results: texts without a word, null or empty, are the empty set and link with each other only; a text of fewer than five words
has one shingle, all of it; sets are told apart by a hash of 64 bits; other columns are not compared.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.llm.common import batches, durable
from backtrail.llm.components import components, keep_least, marked

SHINGLE, WORDS, BLOCKS, WIDTH, NEAR = 5, 8, 14, 31, 5
#: A code word is known by its information bits; behind them go so many bits of the last word, and more before a set's number.
INFORMATION, ALONG, MORE = 26, 33, 23
#: A set's number: its partition and its place there.
NUMBER, PARTITIONS, IN_PARTITION = 40, 1 << 12, 1 << 28
#: Members and hashes of an anchor that are read at once in the second round.
TILE, TILE_HASHES = 1024, 1 << 22
#: Members whose components are combined at once.
GATHERED = 1 << 18
#: The least similarity as a fraction of integers.
LEAST = (4, 5)
#: Bits in which these, and whole fingerprints, of linked sets may differ: four and nine deviations above the mean at ``LEAST``.
MOST_WORD, MOST_BITS = 20, 160
#: Shingle hashes whose bits are counted at once.
BLOCK = 1 << 14


def shingles(text: str | None) -> np.ndarray:
    """Sorted distinct hashes of one whole text's shingles."""
    found = [w.encode() for w in (text or "").lower().split()]
    if not found:
        return np.zeros(0, np.uint64)
    joined, n = b" ".join(found), max(1, len(found) - SHINGLE + 1)
    ends = np.cumsum([len(w) + 1 for w in found]).tolist()
    starts, stops = [0, *ends[: n - 1]], [e - 1 for e in ends[min(SHINGLE, len(found)) - 1 :]]
    digest = xxhash.xxh3_64_intdigest
    return np.unique(np.fromiter((digest(joined[a:b]) for a, b in zip(starts, stops)), np.uint64, n))


def name_of(found: np.ndarray) -> int:
    """Signed hash of a set."""
    return int(np.uint64(xxhash.xxh3_64_intdigest(found.tobytes())).view(np.int64))


def fingerprint(found: np.ndarray) -> np.ndarray:
    """The set's SimHash as ``WORDS`` words; every word counts the bits of another mixing of the shingle hashes."""
    ones = np.zeros((WORDS, 64), np.int64)
    for i in range(0, len(found), BLOCK):
        part = found[i : i + BLOCK]
        for k in range(WORDS):
            mixed = (part ^ np.uint64(0x9E3779B97F4A7C15 * (2 * k + 1) & (1 << 64) - 1)) * np.uint64(0xBF58476D1CE4E5B9 + 2 * k)
            mixed ^= mixed >> np.uint64(31)
            mixed *= np.uint64(0x94D049BB133111EB)
            mixed ^= mixed >> np.uint64(29)
            ones[k] += np.unpackbits(mixed.view(np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return np.packbits(2 * ones > len(found), axis=1).reshape(-1).view(np.int64)


def block_anchors(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``(row, anchor)`` of fingerprints given as rows: all code words within two bits of each block, by block number and information."""
    bits = np.unpackbits(words.view(np.uint8).reshape(len(words), -1), axis=1)[:, : BLOCKS * WIDTH].reshape(len(words), BLOCKS, WIDTH)
    places = np.arange(1, WIDTH + 1)
    syndrome = np.bitwise_xor.reduce(bits * places, axis=2)
    informs = (places & (places - 1)) > 0  # places that are powers of two only check
    bit = np.append(0, np.where(informs, 1 << (np.cumsum(informs) - 1).clip(0), 0))
    value = (bits * bit[1:]).sum(2) | np.arange(BLOCKS) << INFORMATION
    # Flipping places i and i xor syndrome ends in a code word; place 0 stands for no flip.
    flips = np.arange(WIDTH + 1)
    partner = flips ^ syndrome[..., None]
    row, block, at = np.nonzero(flips < partner)
    moved = value[row, block] ^ bit[at] ^ bit[partner[row, block, at]]
    exact_row, exact_block = np.nonzero(syndrome == 0)
    return np.concatenate([row, exact_row]), np.concatenate([moved, value[exact_row, exact_block]])


def alike(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether two sorted sets are similar to the least degree or more."""
    top, bottom = LEAST
    if bottom * min(len(a), len(b)) < top * max(len(a), len(b)):
        return False
    shared = len(np.intersect1d(a, b, assume_unique=True))
    return bottom * shared >= top * (len(a) + len(b) - shared)


def _signing(parts):
    for part in parts:
        sets = [shingles(t) for t in part.column(1).to_pylist()]
        words = np.concatenate([np.zeros(0, np.int64), *(fingerprint(s) for s in sets)])
        lists = pa.ListArray.from_arrays(np.arange(0, len(words) + 1, WORDS, dtype=np.int32), words)
        yield pa.RecordBatch.from_arrays([part.column(0), pa.array([name_of(s) for s in sets], pa.int64()), lists, pa.array([len(s) for s in sets], pa.int64())], ["key", "fp", "words", "n"])


def _anchoring(parts):
    for part in parts:
        names, words = part.column(0).to_numpy(), np.ascontiguousarray(part.column(1).flatten().to_numpy()).reshape(-1, WORDS)
        row, anchor = block_anchors(words)
        more = (words[row, -1] >> ALONG & (1 << MORE) - 1) << NUMBER
        yield pa.RecordBatch.from_arrays([pa.array(anchor << ALONG | words[row, -1] & (1 << ALONG) - 1), pa.array(more | names[row])], ["place", "fp"])


def _meeting(parts):
    """``(anchor, u, v)`` of rows in order: pairs u < v of few members whose words are near; u = v lists a member for the second round."""
    out = lambda *columns: pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["anchor", "u", "v"])
    held = [np.zeros(0, np.int64)] * 3  # the open anchor's members, while they are few
    many = None  # the range's first anchor, then the last one of many members
    for part in parts:
        if not part.num_rows:
            continue
        place, tail = part.column(0).to_numpy(), part.column(1).to_numpy()
        anchor, name, word = map(np.concatenate, zip(held, (place >> ALONG, tail & (1 << NUMBER) - 1, tail >> NUMBER << ALONG | place & (1 << ALONG) - 1)))
        many = anchor[0] if many is None else many
        start = np.flatnonzero(np.append(True, anchor[1:] != anchor[:-1]))
        count = np.diff(np.append(start, len(anchor)))
        large = np.repeat(count > NEAR + 1, count) | (anchor == many)
        done = len(anchor) if large[-1] else start[-1]
        many = anchor[-1] if large[-1] else many
        at = np.flatnonzero(large[:done])
        yield out(anchor[at], name[at], name[at])
        for k in range(1, min(NEAR, done - 1) + 1):
            at = np.flatnonzero((anchor[k:done] == anchor[: done - k]) & ~large[k:done]) + k
            at = at[np.bitwise_count(word[at] ^ word[at - k]) <= MOST_WORD]
            yield out(anchor[at], np.minimum(name[at - k], name[at]), np.maximum(name[at - k], name[at]))
        held = [anchor[done:], name[done:], word[done:]]
    yield out(held[0], held[1], held[1])


def _unfolding(parts):
    for part in parts:
        sets = [shingles(t) for t in part.column(0).to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array([name_of(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["name", "hashes"])


def _confirming(parts):
    for part in parts:
        read = lambda k: (np.frombuffer(x, np.uint64) for x in part.column(k).to_pylist())
        found = pa.array([alike(a, b) for a, b in zip(read(2), read(3))], pa.bool_())
        yield pa.RecordBatch.from_arrays([part.column(0), part.column(1)], ["u", "v"]).filter(found)


def _gathering(parts):
    """``(anchor, root, members, n)`` of rows ``(fp, anchor, root, n)`` in order, a set's own row, then its anchors: what a component has at
    an anchor is one row, as far as the task has read, and not one a member."""

    def combined():
        anchor, root, n = map(np.concatenate, zip(*held))
        order = np.lexsort((root, anchor))
        anchor, root, n = anchor[order], root[order], n[order]
        start = np.flatnonzero(np.append(True, (anchor[1:] != anchor[:-1]) | (root[1:] != root[:-1])))
        columns = anchor[start], root[start], np.diff(np.append(start, len(anchor))), np.add.reduceat(n, start)
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["anchor", "root", "members", "n"])

    held, rows, own = [], 0, np.zeros((2, 1), np.int64)  # the open set's root and size
    for part in parts:
        at = np.flatnonzero(part.column(1).is_valid().to_numpy(zero_copy_only=False))
        first = np.ones(part.num_rows, np.int64)
        first[at] = 0
        facts = np.stack([part.column(k).fill_null(0).to_numpy() for k in (2, 3)])
        facts = np.append(own, facts[:, first > 0], axis=1)
        own = facts[:, -1:]
        if len(at):
            of = np.cumsum(first)[at]
            held.append((part.column(1).fill_null(0).to_numpy()[at], facts[0, of], facts[1, of]))
            rows += len(at)
        if rows >= GATHERED:
            yield combined()
            held, rows = [], 0
    if held:
        yield combined()


def settle(fp: np.ndarray, root: np.ndarray, own: np.ndarray, words: np.ndarray, sets: list[np.ndarray]) -> list[tuple]:
    """Links ``(u, v)`` that join the components ``root`` of members as all their similar pairs do; of two blocks only pairs across."""
    top, bottom = LEAST
    label, size, found = np.unique(root, return_inverse=True)[1], np.array([len(s) for s in sets], np.int64), []
    across = (own != own[0]).any()
    for a in range(len(fp) - 1):
        rest = slice(a + 1, None)
        may = (label[rest] != label[a]) & (bottom * np.minimum(size[rest], size[a]) >= top * np.maximum(size[rest], size[a]))
        at = np.flatnonzero(may & (own[rest] != own[a]) if across else may) + a + 1
        at = at[np.bitwise_count(words[at] ^ words[a]).sum(1, dtype=np.int64) <= MOST_BITS]
        if not len(at):
            continue
        flat = np.concatenate([sets[k] for k in at])
        hit = sets[a][np.searchsorted(sets[a], flat).clip(max=size[a] - 1)] == flat
        shared = np.add.reduceat(hit, np.append(0, np.cumsum(size[at])[:-1]), dtype=np.int64)
        for k in at[bottom * shared >= top * (size[a] + size[at] - shared)]:
            if label[k] != label[a]:
                found.append((min(fp[a], fp[k]), max(fp[a], fp[k])))
                label[label == label[k]] = label[a]
    return found


def _settling(parts):
    """``(u, v)`` of members in the order of their groups (anchor, i, j)."""

    def settled(rows):
        fp, root, own = (np.array([r[k] for r in rows], np.int64) for k in (3, 4, 5))
        found = settle(fp, root, own, np.array([r[6] for r in rows], np.int64).view(np.uint64), [np.frombuffer(r[7], np.uint64) for r in rows])
        return pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], ["u", "v"])

    group, rows = None, []
    for part in parts:
        for row in zip(*(c.to_pylist() for c in part.columns)):
            if row[:3] != group:
                if len(rows) > 1:
                    yield settled(rows)
                group, rows = row[:3], []
            rows.append(row)
    if len(rows) > 1:
        yield settled(rows)


def links(df: DataFrame, signed: DataFrame, text_col: str = "text") -> DataFrame:
    """Links ``(u, v)`` between distinct sets that connect exactly what pairs of the least similarity that meet at anchors connect."""
    distinct = signed.filter("n > 0").groupBy("fp").agg(F.first("words").alias("words"), F.first("n").alias("n"), F.min("key.row").alias("row"))
    fixed = durable(distinct.withColumnRenamed("fp", "name").coalesce(PARTITIONS))
    turn = F.monotonically_increasing_id()
    place = turn.bitwiseAND(F.lit((1 << 33) - 1))
    number = F.shiftright(turn, 33) * IN_PARTITION + F.when(place < IN_PARTITION, place).otherwise(F.raise_error(F.lit("too many sets in a partition")).cast("long"))
    prints = durable(fixed.withColumn("fp", number))
    placed = batches(prints.select("fp", "words"), _anchoring, "place long, fp long")
    dealt = placed.repartitionByRange("place", "fp").sortWithinPartitions("place", "fp")
    met = durable(batches(dealt, _meeting, "anchor long, u long, v long"))

    def unfolded(asked: DataFrame) -> DataFrame:
        """One row stands for each set that is compared; its shingles are taken from the text again."""
        compared = prints.join(asked, "fp", "left_semi").select("row")
        texts = df.join(compared, df["__row"] == compared["row"], "left_semi").select(F.col(text_col).alias("text"))
        sets = batches(texts, _unfolding, "name long, hashes binary").dropDuplicates(["name"])
        return durable(sets.join(prints.select("name", "fp"), "name").select("fp", "hashes"))

    def confirmed(pairs: DataFrame) -> DataFrame:
        side = lambda end, words, n: prints.select(F.col("fp").alias(end), F.col("words").alias(words), F.col("n").alias(n))
        differ = reduce(lambda x, y: x + y, [F.bit_count(F.get("a", F.lit(k)).bitwiseXOR(F.get("b", F.lit(k)))) for k in range(WORDS)])
        sizes = LEAST[1] * F.least("na", "nb") >= LEAST[0] * F.greatest("na", "nb")
        near = durable(pairs.join(side("u", "a", "na"), "u").join(side("v", "b", "nb"), "v").filter(sizes & (differ <= MOST_BITS)).select("u", "v"))
        sets = unfolded(near.select(F.col("u").alias("fp")).unionAll(near.select(F.col("v").alias("fp"))).distinct())
        left, right = sets.select(F.col("fp").alias("u"), F.col("hashes").alias("a")), sets.select(F.col("fp").alias("v"), F.col("hashes").alias("b"))
        return durable(batches(near.join(left, "u").join(right, "v").select("u", "v", "a", "b"), _confirming, "u long, v long"))

    found = confirmed(met.filter("u < v").select("u", "v").distinct())
    roots = components(found)
    nodes = prints.join(roots, prints["fp"] == roots["node"], "left").select("fp", "n", F.coalesce("root", "fp").alias("root"))
    # A set is at an anchor once, so no row of these repeats.
    members = met.filter("u = v").select("anchor", F.col("u").alias("member"))
    none = F.lit(None).cast("long")
    known = nodes.select("fp", none.alias("anchor"), "root", "n").unionAll(members.select("member", "anchor", none, none))
    known = known.repartition("fp").sortWithinPartitions("fp", F.col("anchor").asc_nulls_first())
    gathered = batches(known, _gathering, "anchor long, root long, members long, n long")
    tiles = F.ceil(F.greatest(F.sum("members") / TILE, F.sum("n") / TILE_HASHES)).cast("int").alias("tiles")
    apart = gathered.groupBy("anchor").agg(F.min("root").alias("a"), F.max("root").alias("b"), tiles).filter("a < b").select("anchor", "tiles")
    there = members.join(apart, "anchor")
    left = durable(there.join(nodes, there["member"] == nodes["fp"]).select("anchor", "tiles", "fp", "root"))
    own = F.pmod(F.xxhash64("fp"), F.col("tiles")).cast("int")
    dealt = left.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    dealt = dealt.withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
    carried = unfolded(left.select("fp").distinct()).join(prints.select("fp", "words"), "fp").withColumnRenamed("fp", "set")
    keys = ["anchor", "i", "j"]
    groups = dealt.join(carried, dealt["fp"] == carried["set"]).select(*keys, "fp", "root", "own", "words", "hashes").repartition(*keys).sortWithinPartitions(*keys, "fp")
    joined = found.unionAll(durable(batches(groups, _settling, "u long, v long").distinct()))
    named = lambda end: prints.select(F.col("fp").alias(end), F.col("name").alias(f"{end}_name"))
    return joined.join(named("u"), "u").join(named("v"), "v").select(F.col("u_name").alias("u"), F.col("v_name").alias("v"))


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``df`` that stand for their component, all columns: one row of its smallest id; rows without an id stay."""
    rows = marked(df)
    kind = df.schema[id_col].dataType.simpleString()
    keyed = rows.select(F.struct(F.col(id_col).alias("id"), F.col("__row").alias("row")).alias("key"), F.col(text_col).alias("text"))
    signed = durable(batches(keyed, _signing, f"key struct<id:{kind},row:bigint>, fp long, words array<bigint>, n long"))
    return keep_least(rows, signed.select("key", "fp"), components(links(rows, signed, text_col)), id_col)
