"""Chat formatting by assembly of tokens.

Template of a turn, as text: a marker line of its role, the escaped text, a closing marker::

    ### User: what it says </turn>

The markers are reserved ids above the vocabulary.  Segments are encoded apart and the reserved ids spliced between them, so no
content can become a marker, and no token spans a border.  The loss mask is a prefix sum over +1 where an assistant's text
begins and -1 where it ends.  A role that has no marker of its own is written between the markers ``### Role[`` and ``]:``.

Control strings inside a text are escaped for readers of the rendered text: n back-slashes before one become 2n + 1; reading
back takes them off, so every text survives unchanged.

Defined results: null texts and null roles are empty strings; empty assistant texts add nothing to the loss; rows of equal
conversation and turn follow each other by role, then text; repeated rows are repeated turns; a null conv_id is a
conversation of its own; other columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.llm.byte_bpe import load_ranks
from backtrail.llm.common import batches, once

#: Roles with a marker of their own.
ROLES = ("system", "user", "assistant", "tool")
#: Fixed strings of the template, by their offset above the vocabulary.
MARKERS = (*(f"### {r.capitalize()}: " for r in ROLES), "### Role[", "]: ", " </turn>\n")
OTHER, OTHER_END, END = len(ROLES), len(ROLES) + 1, len(ROLES) + 2
LOSS_ROLE = "assistant"
_CONTROL = r"### (?:System|User|Assistant|Tool):|### Role\[|\]:|</turn>"
_ESCAPE, _UNESCAPE = regex.compile(rf"(\\*)({_CONTROL})"), regex.compile(rf"(\\+)({_CONTROL})")


def escape(text: str) -> str:
    return _ESCAPE.sub(lambda m: m[1] * 2 + "\\" + m[2], text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(lambda m: m[1][: (len(m[1]) - 1) // 2] + m[2], text)


def _library(path: str, pattern: str):
    import tiktoken

    return once(("tiktoken", path, pattern), lambda: tiktoken.Encoding("chat", pat_str=pattern, mergeable_ranks=load_ranks(path), special_tokens={}))


def _assembler(path: str, pattern: str):
    def run(parts):
        library = _library(path, pattern)
        base = library.n_vocab
        for part in parts:
            roles, texts = part.column("role").to_pylist(), part.column("text").to_pylist()
            pieces, begins, ends, sizes, at = [], [], [], [], 0
            for role, text in zip(roles, texts):
                head = [base + ROLES.index(role)] if role in ROLES else [base + OTHER, *library.encode_ordinary(escape(role)), base + OTHER_END]
                body = library.encode_ordinary(escape(text))
                if role == LOSS_ROLE:
                    begins.append(at + len(head))
                    ends.append(at + len(head) + len(body))
                pieces += (head, body, [base + END])
                sizes.append(len(head) + len(body) + 1)
                at += sizes[-1]
            step = np.zeros(at + 1, np.int8)
            np.add.at(step, begins, 1)
            np.add.at(step, ends, -1)
            mask = np.cumsum(step[:-1]).astype(bool)
            offsets = np.cumsum([0, *sizes]).astype(np.int32)
            ids = pa.ListArray.from_arrays(offsets, np.fromiter((i for p in pieces for i in p), np.int32, at))
            yield pa.RecordBatch.from_arrays([*(part.column(c) for c in ("conv_id", "turn", "role", "text")), ids, pa.ListArray.from_arrays(offsets, pa.array(mask))], ["conv_id", "turn", "role", "text", "input_ids", "loss_mask"])

    return run


def format_turns(df: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """``(conv_id, turn, role, text, input_ids array<int>, loss_mask array<boolean>)`` of every turn, row by row."""
    kinds = {c: df.schema[c].dataType.simpleString() for c in ("conv_id", "turn")}
    turns = df.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return batches(turns, _assembler(ranks_path, pattern), f"conv_id {kinds['conv_id']}, turn {kinds['turn']}, role string, text string, input_ids array<int>, loss_mask array<boolean>")


def in_order(turns: DataFrame) -> DataFrame:
    """Conversations whole in one partition each, one after the other, turns in order.  Sorting spills; no conversation is gathered in memory."""
    return turns.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


class _Reader:
    """Reads one conversation back from its tokens, turn by turn."""

    def __init__(self, conv_id):
        self.conv_id, self.turns, self.loss_chars, self.chars = conv_id, 0, 0, 0
        self.said, self.loss = hashlib.sha256(), hashlib.sha256()

    def add(self, ids: np.ndarray, mask: np.ndarray, library) -> None:
        base = library.n_vocab
        text = lambda part: library.decode(part.tolist())
        marks = np.flatnonzero(ids >= base)
        self.chars += sum(len(MARKERS[i - base]) for i in ids[marks].tolist())
        if ids[0] == base + OTHER:
            role, first = text(ids[1 : marks[1]]), marks[1] + 1
            self.chars += len(role)
            role = unescape(role)
        else:
            role, first = ROLES[ids[0] - base], 1
        content = text(ids[first : marks[-1]])
        self.chars += len(content)
        self.said.update(f"{role}\n{unescape(content)}\n".encode())
        learned = unescape(text(ids[mask]))
        self.loss.update(learned.encode())
        self.loss_chars += len(learned)
        self.turns += 1

    def row(self) -> tuple:
        return self.conv_id, self.turns, self.said.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.chars


def _reading(path: str, pattern: str, schema: pa.Schema):
    def run(parts):
        library, reader = _library(path, pattern), None
        for part in parts:
            done = []
            lists, masks = part.column("input_ids"), part.column("loss_mask")
            offsets, ids = np.asarray(lists.offsets), np.asarray(lists.values)
            bits, shift = masks.values.to_numpy(zero_copy_only=False), masks.offsets[0].as_py() - int(offsets[0])
            for i, conv_id in enumerate(part.column("conv_id").to_pylist()):
                if reader is None or reader.conv_id != conv_id:
                    if reader is not None:
                        done.append(reader.row())
                    reader = _Reader(conv_id)
                a, b = offsets[i], offsets[i + 1]
                reader.add(ids[a:b], bits[a + shift : b + shift].astype(bool), library)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*done) if done else [[]] * 6, schema.types)], schema=schema)
        if reader is not None:
            yield pa.RecordBatch.from_arrays([pa.array([c], k) for c, k in zip(reader.row(), schema.types)], schema=schema)

    return run


def read_back(turns: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """One row per conversation of :func:`format_turns`, read from its tokens and masks alone, in one streaming pass."""
    from pyspark.sql.pandas.types import to_arrow_type

    kind = turns.schema["conv_id"].dataType
    schema = pa.schema([("conv_id", to_arrow_type(kind)), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])
    ordered = in_order(turns).select("conv_id", "input_ids", "loss_mask")
    return batches(ordered, _reading(ranks_path, pattern, schema), f"conv_id {kind.simpleString()}, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
