"""Token counts by rank-synchronous merging of ragged arrays.

The pre-tokens a batch has not met before lie end to end in one integer array.  A round finds, by a segmented minimum, the
lowest-rank pair of every sequence and merges all of them at once; sequences without a mergeable pair leave.  The count of a
pre-token is the number of symbols that survive.

Within a round all non-overlapping occurrences of a sequence's pair merge, from the left.  That equals one merge at a time
when no merge that uses a symbol ranks before a merge that makes it; :class:`MergeTable` checks this of the vocabulary, and
else only the leftmost occurrence merges in a round.

Defined results: a null text has 0 bytes and 0 tokens; the special strings of the vocabulary count as one token each where they
stand in a text, which is that library's default; equal rows give equal rows; other columns are not read.
"""

from __future__ import annotations

import json
import unicodedata

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.llm.common import batches, once

#: Distinct pre-tokens that a worker remembers before it starts afresh.
MEMO = 500_000


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class MergeTable:
    """Ranked pairs as sorted integer keys."""

    def __init__(self, vocab: dict[str, int], merges: list[tuple[str, str]]):
        self.width = max(vocab.values(), default=0) + 1
        left = np.array([vocab[a] for a, _ in merges], np.int64)
        right = np.array([vocab[b] for _, b in merges], np.int64)
        made = np.array([vocab[a + b] for a, b in merges], np.int64)
        keys = left * self.width + right
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank, self.made = keys[order], order.astype(np.int64), made[order]
        last = np.full(self.width, -1)
        np.maximum.at(last, made, np.arange(len(merges)))
        self.ordered = bool((np.maximum(last[left], last[right]) < np.arange(len(merges))).all())

    def find(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank of every pair, or the number of merges; and its place in the table."""
        key = a * self.width + b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.rank[at], len(self.keys)), at


def merged_counts(symbols: np.ndarray, lengths: np.ndarray, table: MergeTable) -> np.ndarray:
    """Surviving symbols of each sequence of the ragged array; every length is at least 1."""
    out, live = lengths.copy(), np.arange(len(lengths))
    none = len(table.keys)
    while len(live):
        ends = np.cumsum(lengths)
        rank, at = table.find(symbols[:-1], symbols[1:])
        rank, at = np.append(rank, none), np.append(at, 0)
        rank[ends - 1] = none  # no pair crosses into the next sequence
        lowest = np.minimum.reduceat(rank, ends - lengths)
        hit = (rank == np.repeat(lowest, lengths)) & (rank < none)
        # Of a run of adjacent hits, which overlap, every second one stays, from the first.
        where = np.flatnonzero(hit)
        if len(where):
            fresh = np.append(True, np.diff(where) > 1)
            first = np.maximum.accumulate(np.where(fresh, np.arange(len(where)), 0))
            where = where[(np.arange(len(where)) - first) % 2 == 0]
            owner = np.searchsorted(ends, where, side="right")
            if not table.ordered:
                leftmost = np.append(True, np.diff(owner) > 0)
                where, owner = where[leftmost], owner[leftmost]
            symbols[where] = table.made[at[where]]
            stay = np.ones(len(symbols), bool)
            stay[where + 1] = False
            lengths = lengths - np.bincount(owner, minlength=len(lengths))
        else:
            stay = np.ones(len(symbols), bool)
        out[live] = lengths
        going = (lowest < none) & (lengths > 1)
        rows = np.repeat(going, np.diff(ends, prepend=0))
        symbols, lengths, live = symbols[stay & rows], lengths[going], live[going]
    return out


class Counter:
    """Token counts of texts by one vocabulary file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.vocab, self.table, self.memo = model["vocab"], MergeTable(model["vocab"], merges), {}
        self.suffix = model.get("end_of_word_suffix") or ""
        letters = byte_letters()
        self.inner = np.array([self.vocab[x] for x in letters], np.int64)
        self.final = np.array([self.vocab[x + self.suffix] for x in letters], np.int64)
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.find = regex.compile(split["pattern"]["Regex"].replace(r"\s", r"\p{White_Space}")).findall
        special = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None

    def pieces(self, text: str) -> tuple[list[str], int]:
        """Pre-tokens, and the number of special strings."""
        parts = self.special.split(text) if self.special and "<|" in text else [text]
        found = []
        for part in parts:
            if not part.isascii():
                part = unicodedata.normalize("NFC", part).replace("Σ", "σ")  # no rule for a final sigma
            found += self.find(part.lower())
        return found, len(parts) - 1

    def learn(self, pieces) -> None:
        if len(self.memo) > MEMO:
            self.memo.clear()
        pieces = list(pieces)
        raw = [p.encode() for p in pieces]
        lengths = np.fromiter(map(len, raw), np.int64, len(raw))
        flat = np.frombuffer(b"".join(raw), np.uint8)
        symbols = self.inner[flat]
        last = np.cumsum(lengths) - 1
        symbols[last] = self.final[flat[last]]
        self.memo.update(zip(pieces, merged_counts(symbols, lengths, self.table).tolist()))

    def count(self, texts) -> list[int]:
        split = [self.pieces(t or "") for t in texts]
        unknown = {p for pieces, _ in split for p in pieces if p not in self.memo}
        if unknown:
            known = len(self.memo)
            self.learn(unknown)
            if len(self.memo) < known + len(unknown):  # the memo was cleared
                self.learn({p for pieces, _ in split for p in pieces if p not in self.memo})
        get = self.memo.__getitem__
        return [sum(map(get, pieces)) + extra for pieces, extra in split]


def _counting(path: str):
    def run(parts):
        counter = once(("counter", path), lambda: Counter(path))
        for part in parts:
            counts = pa.array(counter.count(part.column(1).to_pylist()), pa.int64())
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), counts], ["id", "n_bytes", "n_tokens"])

    return run


def count_tokens(df: DataFrame, path: str, limit: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, n_bytes, n_tokens, over_limit)`` of every row's whole text."""
    kind = df.schema[id_col].dataType.simpleString()
    text = F.coalesce(F.col(text_col), F.lit(""))
    counted = batches(df.select(F.col(id_col).alias("id"), text.alias("text"), F.octet_length(text).cast("long").alias("n_bytes")), _counting(path), f"id {kind}, n_bytes long, n_tokens long")
    return counted.select(F.col("id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
