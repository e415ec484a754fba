"""Byte-level BPE with a two-tier lookup.

Tier one is a minimal perfect hash over the whole vocabulary: a pre-token that is itself a vocabulary entry takes its id
from one probe and one comparison of bytes.  Tier two merges the others with a heap of ranked pairs over linked bytes, in
O(n log n) for a pre-token of n bytes.

Defined results: a null text is an empty text and has no ids; ids of an empty list decode to no bytes; equal rows give
equal rows; other columns of the input are not read, whatever their names.
"""

from __future__ import annotations

import base64
import heapq
from itertools import chain, islice

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.llm.common import batches, once

#: Distinct pre-tokens that a worker remembers before it starts afresh.
MEMO = 400_000


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def _mixed(h: np.ndarray, salt: int) -> np.ndarray:
    h = h + np.uint64((salt * 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF)
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def _digests(keys) -> np.ndarray:
    return np.fromiter((xxhash.xxh3_64_intdigest(k) for k in keys), np.uint64, len(keys))


class PerfectHash:
    """Minimal perfect hash of a fixed key set: a key settles on the first level where no other remaining key shares its bit."""

    def __init__(self, keys: list[bytes]):
        digests = _digests(keys)
        left, level, taken, self.starts = np.arange(len(keys)), 0, [], [0]
        while left.size:
            width = 2 * left.size
            slot = (_mixed(digests[left], level) % np.uint64(width)).astype(np.int64)
            alone = np.bincount(slot, minlength=width)[slot] == 1
            bits = np.zeros(width, bool)
            bits[slot[alone]] = True
            taken.append(bits)
            self.starts.append(self.starts[-1] + width)
            left, level = left[~alone], level + 1
        self.bits = np.concatenate(taken) if taken else np.zeros(0, bool)
        self.rank = np.cumsum(self.bits) - 1

    def __call__(self, keys) -> np.ndarray:
        """An index below the number of keys, distinct for distinct keys; for strangers any index or -1."""
        digests, out = _digests(keys), np.full(len(keys), -1)
        left = np.arange(len(keys))
        for level, start in enumerate(self.starts[:-1]):
            if not left.size:
                break
            width = self.starts[level + 1] - start
            slot = start + (_mixed(digests[left], level) % np.uint64(width)).astype(np.int64)
            hit = self.bits[slot]
            out[left[hit]] = self.rank[slot[hit]]
            left = left[~hit]
        return out


class _Numbers(dict):
    """Numbers strings in the order they are first looked up."""

    def __missing__(self, key):
        self[key] = n = len(self)
        return n


def gathered(flat: np.ndarray, begins: np.ndarray, widths: np.ndarray) -> np.ndarray:
    """The runs ``flat[begin : begin + width]``, end to end."""
    ends = np.cumsum(widths)
    return flat[np.repeat(begins - (ends - widths), widths) + np.arange(ends[-1] if len(ends) else 0)]


class Codec:
    """Ids of texts and bytes of ids, by one rank file and one pre-token pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks = ranks
        self._forget()
        # The pattern's \s is the White_Space property; this module's own \s has four control characters more.
        self.find = regex.compile(pattern.replace(r"[^\s", r"[^\p{White_Space}").replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}")).findall
        keys = list(ranks)
        self.hash = PerfectHash(keys)
        self.keys, self.ids = [b""] * len(keys), [0] * len(keys)
        for key, i in zip(keys, self.hash(keys)):
            self.keys[i], self.ids[i] = key, ranks[key]
        size = max(ranks.values(), default=-1) + 1
        by_id = [b""] * size
        for key, rank in ranks.items():
            by_id[rank] = key
        self.widths = np.fromiter(map(len, by_id), np.int64, size)
        self.begins = np.cumsum(self.widths) - self.widths
        self.bytes = np.frombuffer(b"".join(by_id), np.uint8)

    def merged(self, piece: bytes) -> list[int]:
        ranks, n = self.ranks, len(piece)
        ends, after, before = list(range(1, n + 1)), list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(rank, i, i + 2) for i in range(n - 1) if (rank := ranks.get(piece[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, end = heapq.heappop(heap)
            j = after[i]
            if ends[i] < 0 or j >= n or ends[j] != end or ends[i] != j:
                continue  # one of the two has been merged meanwhile
            ends[i], ends[j], after[i] = end, -1, after[j]
            if after[i] < n:
                before[after[i]] = i
                if (rank := ranks.get(piece[i : ends[after[i]]])) is not None:
                    heapq.heappush(heap, (rank, i, ends[after[i]]))
            if (k := before[i]) >= 0 and (rank := ranks.get(piece[k:end])) is not None:
                heapq.heappush(heap, (rank, k, end))
        i, out = 0, []
        while i < n:
            out.append(ranks[piece[i : ends[i]]])
            i = after[i]
        return out

    def _forget(self) -> None:
        """Pre-tokens by number; the ids of number i are ``known[starts[i] : starts[i + 1]]``."""
        self.memo, self.known, self.starts = _Numbers(), np.zeros(0, np.int32), np.zeros(1, np.int64)

    def _learn(self) -> None:
        """Ids of the pre-tokens that got a number since last time."""
        fresh = [p.encode() for p in islice(self.memo, len(self.starts) - 1, None)]
        lists = [[self.ids[i]] if i >= 0 and self.keys[i] == raw else self.merged(raw) for raw, i in zip(fresh, self.hash(fresh).tolist())]
        widths = np.fromiter(map(len, lists), np.int64, len(lists))
        self.known = np.concatenate([self.known, np.fromiter(chain.from_iterable(lists), np.int32, int(widths.sum()))])
        self.starts = np.concatenate([self.starts, self.starts[-1] + np.cumsum(widths)])

    def encode_flat(self, texts) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts end to end, and the offsets between texts."""
        if len(self.memo) > MEMO:
            self._forget()
        number, found, counts = self.memo.__getitem__, [], []
        for text in texts:
            pieces = self.find(text or "")
            found.append(np.fromiter(map(number, pieces), np.int64, len(pieces)))
            counts.append(len(pieces))
        if len(self.memo) >= len(self.starts):
            self._learn()
        numbers = np.concatenate(found) if found else np.zeros(0, np.int64)
        widths = np.diff(self.starts)[numbers]
        ends = np.concatenate(([0], np.cumsum(widths)))
        return gathered(self.known, self.starts[numbers], widths), ends[np.cumsum([0, *counts])]

    def encode(self, texts) -> list[list[int]]:
        flat, offsets = self.encode_flat(texts)
        return [flat[a:b].tolist() for a, b in zip(offsets, offsets[1:])]

    def decode_flat(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All bytes of a run of ids, and where each id's bytes end."""
        widths = self.widths[ids]
        return gathered(self.bytes, self.begins[ids], widths), np.cumsum(widths)


def _codec(path: str, pattern: str) -> Codec:
    return once(("codec", path, pattern), lambda: Codec(load_ranks(path), pattern))


def _encoder(path: str, pattern: str):
    def run(parts):
        codec = _codec(path, pattern)
        for part in parts:
            flat, offsets = codec.encode_flat(part.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(offsets.astype(np.int32), flat)], ["id", "ids"])

    return run


def _decoder(path: str, pattern: str):
    def run(parts):
        codec = _codec(path, pattern)
        for part in parts:
            lists = part.column(1)
            offsets = np.asarray(lists.offsets)
            raw, ends = codec.decode_flat(np.asarray(lists.values)[offsets[0] : offsets[-1]])
            cut = np.concatenate(([0], ends))[offsets - offsets[0]].astype(np.int32)
            decoded = pa.Array.from_buffers(pa.binary(), len(lists), [None, pa.py_buffer(cut), pa.py_buffer(np.ascontiguousarray(raw))])
            yield pa.RecordBatch.from_arrays([part.column(0), lists, decoded], ["id", "ids", "decoded"])

    return run


def _round_trip(path: str, pattern: str):
    def run(parts):
        return _decoder(path, pattern)(_encoder(path, pattern)(parts))

    return run


def encode(df: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, ids array<int>)`` of every row, the whole text, without special tokens."""
    kind = df.schema[id_col].dataType.simpleString()
    return batches(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), _encoder(ranks_path, pattern), f"id {kind}, ids array<int>").withColumnRenamed("id", id_col)


def decode(df: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """``(id_col, ids, decoded binary)`` of every row; a null list decodes as an empty one."""
    kind = df.schema[id_col].dataType.simpleString()
    ids = F.coalesce(F.col(ids_col), F.array().cast("array<int>"))
    return batches(df.select(F.col(id_col).alias("id"), ids.alias("ids")), _decoder(ranks_path, pattern), f"id {kind}, ids array<int>, decoded binary").withColumnRenamed("id", id_col)


def round_trip(df: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, ids, decoded binary)``: :func:`encode`, then :func:`decode`, in one pass through one worker."""
    kind = df.schema[id_col].dataType.simpleString()
    return batches(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), _round_trip(ranks_path, pattern), f"id {kind}, ids array<int>, decoded binary").withColumnRenamed("id", id_col)


def digests(df: DataFrame, ranks_path: str, pattern: str, ids: bool = False) -> DataFrame:
    """Encodes and decodes ``documents``: counts and digests of the ids and of the decoded bytes, with ``ids`` the ids too."""
    both = round_trip(df, ranks_path, pattern)
    return both.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        *(["ids"] if ids else []),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), " "), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
