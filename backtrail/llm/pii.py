"""Personal data by a linear-chain conditional random field over word shapes, beside fixed base patterns.

The field is trained by gradient ascent from a small labelled table (``MAX_TRAINING`` rows at most): its features are hashed
properties of a word's shape and of its neighbours' shapes, plus a few cue words of the table.  Words of equal shape share their
scores, so a batch is scored by gathering rows of three small tables.

Decoding is exact Viterbi in numpy batches.  A word whose margin for "nothing" exceeds all that transitions could return is
certainly nothing on the best path; such words part a text into short runs, which are decoded side by side.

Base spans (e-mail, ip, card, phone) always stay.  A decoded span, of whatever kind, is added if it overlaps no base span: local phone
numbers, secrets, and numbers that a base pattern runs together with what stands beside them.  A decoded card or ip must be one by its
check digit or range: what only looks like it is to be left alone.

Defined results: null texts are empty and have no spans; offsets are code points, end exclusive; equal rows get equal rows;
other columns are not read (``redact`` returns all of them).
"""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from backtrail.llm.common import batches, once

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "secret")
LABELS = ("O", *(f"{p}-{k}" for k in KINDS for p in "BI"))
FEATURES, MAX_TRAINING, ROUNDS, RATE, PENALTY, MEMO = 4096, 20_000, 60, 0.25, 0.02, 300_000

_AT = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    found = [int(c) for c in reversed(digits)]
    return (sum(found[::2]) + sum(sum(divmod(2 * d, 10)) for d in found[1::2])) % 10 == 0


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def _octets(text: str) -> bool:
    """Whether all parts are at most 255, however many zeros lead them."""
    return all(len(p) <= 3 and int(p or "0") <= 255 for p in (p.lstrip("0") for p in text.split(".")))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """``(start, kind index, end)`` of the base patterns, leftmost and non-overlapping per kind, in time linear in the text."""
    out, end = [], 0
    if "@" in text:
        for m in _AT.finditer(text):
            start = m.start()
            while start > end and text[start - 1] in _LOCAL:
                start -= 1
            if start < m.start():
                out.append((start, 0, m.end()))
                end = m.end()
    if any(c in text for c in "0123456789"):
        for m in _IP.finditer(text):
            if _octets(m[0]):
                out.append((m.start(), 1, m.end()))
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 14 and 14 <= len(d := _digits(m[0])) <= 19 and luhn(d):
                out.append((m.start(), 2, m.end()))
        if "+" in text:
            for m in _PHONE.finditer(text):
                if 10 <= len(_digits(m[0])) <= 15:
                    out.append((m.start(), 3, m.end()))
    return sorted(out)


# --- word shapes -------------------------------------------------------------------------------------------------------

_MARKS = "\"'.,;:!?()[]{}<>|*#$%&`"


def _runs(core: str) -> str:
    """Classes of a word's characters, runs as one; runs of digits keep a bucket of their length."""
    out, last, length = [], "", 0
    for c in [*core, ""]:
        kind = "9" if "0" <= c <= "9" else "A" if c.isupper() else "a" if c.isalpha() else c
        if kind != last:
            if last == "9":
                out[-1] = f"9{length if length < 5 else 5 if length < 10 else 10 if length < 14 else 14 if length < 20 else 20}"
            if kind:
                out.append(kind)
            last, length = kind, 0
        length += 1
    return "".join(out)


def shape(word: str, cues: frozenset) -> tuple[str, ...]:
    """What the field sees of a word; a few values, so that many words share theirs."""
    if word.isalpha():
        cue = word.lower() if len(word) <= 12 and word.lower() in cues else ""
        return "a" if word.islower() else "A" if word.isupper() else "Aa", f"cue {cue}"
    core = word.strip(_MARKS)
    low = core.lower()
    hexed = len(core) >= 16 and all(c in "0123456789abcdef" for c in low) and not low.isdigit() and not low.isalpha()
    mixed = len(core) >= 12 and any(c.isdigit() for c in core) and any(c.isalpha() for c in core) and low.isalnum()
    number = _digits(core)
    checked = 14 <= len(number) <= 19 and len(number) == len(core) and luhn(number)
    runs = "hex" if hexed else "mixed" if mixed else _runs(core)
    cue = low if low in cues else word if word in cues else ""
    return runs, f"cue {cue}", f"quoted {word[:1] in _QUOTES}", f"at {'@' in core}", f"dots {min(core.count('.'), 4)}", f"checked {checked}", f"plus {core[:1] == '+'}", f"brackets {word[:1] == '('}", f"digits {min(len(number), 20) // 4}"


_QUOTES = "\"'`"


def _hashed(features) -> list[int]:
    return [xxhash.xxh64_intdigest(f.encode(), 1) % FEATURES for f in ("any", *features)]


# --- the labelled table ------------------------------------------------------------------------------------------------


def labelled_table(spark: SparkSession, sentences: int = 600, seed: int = 11) -> DataFrame:
    """A small labelled table ``(sentence, position, word, tag)``, drawn by rule: invented words around planted items and decoys."""
    return spark.createDataFrame(labelled_rows(sentences, seed), "sentence long, position long, word string, tag string")


def labelled_rows(sentences: int, seed: int) -> list[tuple]:
    rng = random.Random(seed)
    pick = rng.choice
    syllables = "the and er on re ing ly ción que ado ment eau ung lich der pf zu la es ti ou ha".split()
    word = lambda: "".join(pick(syllables) for _ in range(rng.randint(1, 4)))
    digits = lambda n: "".join(pick("0123456789") for _ in range(n))
    hexed = lambda n: "".join(pick("0123456789abcdef") for _ in range(n))

    def number(valid: bool) -> str:
        while True:
            n = digits(16)
            if luhn(n) == valid:
                return n

    def dealt(n: str, by: str) -> str:
        return by.join(n[i : i + 4] for i in range(0, len(n), 4))

    def item() -> tuple[str, str]:
        kind = pick(KINDS)
        if kind == "email":
            return pick((f"{word()}.{digits(2)}@mail{digits(1)}.example.com", f"{word()}@{word()}.org", f"{word()}_{word()}@{word()}.{word()}.net")), kind
        if kind == "ip":
            return ".".join(str(rng.randint(1, 255)) for _ in range(4)), kind
        if kind == "card":
            return pick((number(True), dealt(number(True), " "), dealt(number(True), "-"))), kind
        if kind == "phone":
            return pick((f"+1 ({digits(3)}) 555-{digits(4)}", f"+49 {digits(3)} {digits(7)}", f"+{digits(11)}", f"({digits(3)}) {digits(3)}-{digits(4)}", f"{digits(3)}-{digits(3)}-{digits(4)}")), kind
        coded = lambda n: "".join(pick("ABCDEFGHJKLMNPQRSTUVWXYZabcdefghijkmnopqrstuvwxyz23456789") for _ in range(n))
        return pick((hexed(40), hexed(32), hexed(64), pick("AZ") + hexed(19).upper(), "".join(pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567") for _ in range(20)), coded(rng.randint(24, 44)), f"{word()[:3]}_{coded(rng.randint(20, 40))}", word() + digits(4) + word() + digits(5) + word())), kind

    def decoy() -> str:
        return pick((number(False), digits(rng.randint(1, 12)), f"{digits(1)}.{digits(1)}.", f"{digits(2)}.{digits(3)}", f"{digits(4)}-{digits(2)}-{digits(2)}", f"${digits(2)}.{digits(2)}", f"https://{word()}.org/{word()}/{digits(3)}", f"({word()})", word().upper() + "!!", word() + pick(("***", "&&&", "###", "%%%", "$$$")), "|", "=", '"' + word() + '"', f"{word()}-{word()}", f"{word()}={digits(1)}", f"{word()},", f"v{digits(1)}.{digits(1)}.{digits(1)}", word() + digits(1)))

    rows = []
    for s in range(sentences):
        words: list[tuple[str, str]] = []
        for _ in range(rng.randint(2, 5)):
            for _ in range(rng.randint(0, 4)):
                w = word() + pick(("", "", "", ",", "."))
                words.append((pick((w, w.capitalize(), w, w.upper())), "O"))
            if rng.random() < 0.45:
                words.append((decoy(), "O"))
                continue
            text, kind = item()
            tail = pick(("", "", "", ".", ",", "***", "###", "&&&", "!!"))
            if kind == "secret":
                lead = pick(("token", "key", "secret", "api_key", "password", "bearer", "access_key", "client_secret"))
                words += [pick(((lead, "O"), (lead.upper(), "O")))] + ([("=", "O")] if rng.random() < 0.8 else [(":", "O")])
                text = f'"{text}"' if rng.random() < 0.7 else text
            parts = (text + tail).split(" ")
            words += [(p, f"{'B' if i == 0 else 'I'}-{kind}") for i, p in enumerate(parts)]
        rows += [(s, i, w, t) for i, (w, t) in enumerate(words)]
    return rows


# --- the field ---------------------------------------------------------------------------------------------------------


def _softmax(x: np.ndarray, axis: int) -> tuple[np.ndarray, np.ndarray]:
    top = x.max(axis, keepdims=True)
    e = np.exp(x - top)
    total = e.sum(axis, keepdims=True)
    return e / total, (np.log(total) + top).squeeze(axis)


class Field:
    """Weights of a trained field: ``(3, FEATURES, labels)`` for the word before, the word and the word after; transitions."""

    def __init__(self, weights: np.ndarray, moves: np.ndarray, cues: frozenset):
        self.weights, self.moves, self.cues = weights, moves, cues
        gain_in = (moves[:, None, :] - moves[:, None, :1]).max(0)[0]  # label instead of O, after any label
        gain_out = (moves - moves[:1]).max(1)  # label instead of O, before any label
        self.need = np.maximum(gain_in, 0) + np.maximum(gain_out, 0)  # at least 0: a text has ends

    @classmethod
    def train(cls, table: DataFrame) -> Field:
        """From a table ``(sentence, position, word, tag)``; a bounded number of rows comes to the driver."""
        rows = table.filter("word is not null and tag is not null").orderBy("sentence", "position").limit(MAX_TRAINING).collect()
        return cls.of_rows([(r["sentence"], r["word"], r["tag"]) for r in rows])

    @classmethod
    def of_rows(cls, rows: list[tuple]) -> Field:
        near, counts = {}, {}
        for (s, w, t), after in zip(rows, [*rows[1:], (None, "", "O")]):
            if t == "O" and after[0] == s:
                near[w.lower()] = near.get(w.lower(), 0) + (after[2] != "O")
                counts[w.lower()] = counts.get(w.lower(), 0) + 1
        cues = frozenset(w for w, n in near.items() if n >= 10 and 2 * n > counts[w])
        field = cls(np.zeros((3, FEATURES, len(LABELS))), np.zeros((len(LABELS), len(LABELS))), cues)
        sentences: dict = {}
        for s, w, t in rows:
            sentences.setdefault(s, []).append((w, LABELS.index(t)))
        sentences = sorted(sentences.values(), key=len, reverse=True)
        if not sentences:
            field.weights[:, :, 0] = 1.0
            return cls(field.weights, field.moves, cues)
        length, n = len(sentences[0]), len(LABELS)
        keys: dict = {None: 0}
        ids = np.zeros((len(sentences), length + 2), np.int64)
        tags, live = np.zeros((len(sentences), length), np.int64), np.zeros((len(sentences), length), bool)
        for i, words in enumerate(sentences):
            for j, (w, t) in enumerate(words):
                ids[i, j + 1] = keys.setdefault(shape(w, cues), len(keys))
                tags[i, j], live[i, j] = t, True
        hashed = [[] if k is None else _hashed(k) for k in keys]
        owner, feature = np.repeat(np.arange(len(keys)), [len(h) for h in hashed]), np.array([f for h in hashed for f in h])
        gold = np.eye(n)[tags] * live[..., None]
        around = [ids[:, k : k + length] for k in range(3)]
        first, second, step = [0.0, 0.0], [0.0, 0.0], 0
        gold_moves = np.einsum("sti,stj->ij", gold[:, :-1], gold[:, 1:])
        for step in range(1, ROUNDS + 1):
            rows_of = np.zeros((3, len(keys), n))
            for k in range(3):
                np.add.at(rows_of[k], owner, field.weights[k][feature])
            emit = sum(rows_of[k][around[k]] for k in range(3))
            ahead, back = np.zeros_like(emit), np.zeros_like(emit)
            ahead[:, 0] = emit[:, 0]
            for t in range(1, length):
                ahead[:, t] = _softmax(ahead[:, t - 1, :, None] + field.moves, 1)[1] + emit[:, t]
            for t in range(length - 2, -1, -1):
                found = _softmax(field.moves + (emit[:, t + 1] + back[:, t + 1])[:, None, :], 2)[1]
                back[:, t] = np.where(live[:, t + 1, None], found, 0.0)
            belief = _softmax(ahead + back, 2)[0] * live[..., None]
            pairs = np.zeros((n, n))
            for t in range(length - 1):
                joint = ahead[:, t, :, None] + field.moves + (emit[:, t + 1] + back[:, t + 1])[:, None, :]
                flat = _softmax(joint.reshape(len(joint), -1), 1)[0] * live[:, t + 1, None]
                pairs += flat.sum(0).reshape(n, n)
            error = gold - belief
            slope = np.zeros_like(field.weights)
            for k in range(3):
                per_key = np.zeros((len(keys), n))
                np.add.at(per_key, around[k].ravel(), error.reshape(-1, n))
                np.add.at(slope[k], feature, per_key[owner])
            for i, (value, up) in enumerate(((field.weights, slope), (field.moves, gold_moves - pairs))):
                up = up - PENALTY * value
                first[i] = 0.8 * first[i] + 0.2 * up
                second[i] = 0.95 * second[i] + 0.05 * up * up
                value += RATE * (first[i] / (1 - 0.8**step)) / (np.sqrt(second[i] / (1 - 0.95**step)) + 1e-8)
        return cls(field.weights, field.moves, cues)


class Decoder:
    """Decodes texts by a field; shapes and words seen are remembered within a bound."""

    def __init__(self, field: Field):
        self.field = field
        self._clear()

    def _clear(self) -> None:
        self.words, self.keys, self.rows = {}, {}, np.zeros((3, 1, len(LABELS)))

    def indices(self, words: list[str]) -> np.ndarray:
        if len(self.words) > MEMO:
            self._clear()
        fresh = []
        for w in set(words).difference(self.words):
            key = shape(w, self.field.cues)
            if key not in self.keys:
                self.keys[key] = len(self.keys) + 1
                fresh.append(self.field.weights[:, _hashed(key)].sum(1))
            self.words[w] = self.keys[key]
        if fresh:
            self.rows = np.concatenate([self.rows, np.stack(fresh, 1)], 1)
        return np.fromiter(map(self.words.__getitem__, words), np.int64, len(words))

    def labels(self, words: list[str], starts: np.ndarray) -> np.ndarray:
        """Label of every word of sequences that lie end to end; ``starts`` marks where each begins."""
        ids = self.indices(words)
        before, after = np.append(0, ids[:-1]), np.append(ids[1:], 0)
        before[starts] = 0
        after[starts[1:] - 1] = 0
        emit = self.rows[0][before] + self.rows[1][ids] + self.rows[2][after]
        out = np.zeros(len(ids), np.int64)
        unsure = (emit[:, 1:] + self.field.need[1:] >= emit[:, :1]).any(1)
        if not unsure.any():
            return out
        # Runs of unsure words; a word next to a run's border, within its sequence, is surely O.
        begin = unsure & np.append(True, ~unsure[:-1])
        begin[starts] = unsure[starts]
        at = np.flatnonzero(begin)
        stop = unsure & np.append(~unsure[1:], True)
        stop[starts[1:] - 1] = unsure[starts[1:] - 1]
        ends = np.flatnonzero(stop) + 1
        heads = np.zeros(len(ids) + 1, bool)
        heads[starts] = True
        heads[len(ids)] = True
        order = np.argsort(at - ends, kind="stable")
        at, ends = at[order], ends[order]
        sizes = ends - at
        moves = self.field.moves
        score = emit[at] + np.where(heads[at][:, None], 0.0, moves[0])
        backs = []
        for t in range(1, int(sizes[0])):
            n = int(np.searchsorted(-sizes, -t, side="left"))  # runs longer than t, which come first
            joint = score[:n, :, None] + moves
            best = joint.argmax(1)
            backs.append(best)
            score[:n] = np.take_along_axis(joint, best[:, None, :], 1)[:, 0] + emit[at[:n] + t]
        label = (score + np.where(heads[ends][:, None], 0.0, moves[:, 0])).argmax(1)
        for t in range(int(sizes[0]) - 1, -1, -1):
            n = int(np.searchsorted(-sizes, -t, side="left"))
            out[at[:n] + t] = label[:n]
            if t:
                label[:n] = backs[t - 1][np.arange(n), label[:n]]
        return out

    def spans(self, texts: list[str]) -> list[list[tuple[int, int, int]]]:
        """Decoded spans ``(start, kind index, end)`` of every text, marks around words cut off."""
        words, starts, lines = [], [], []
        for i, text in enumerate(texts):
            at = 0
            for line in text.split("\n"):
                if found := line.split():
                    starts.append(len(words))
                    lines.append((i, at, line))
                    words += found
                at += len(line) + 1
        out: list[list] = [[] for _ in texts]
        if not words:
            return out
        begins = np.array(starts)
        labels = self.labels(words, begins)
        hits = np.flatnonzero(labels)
        for n in np.unique(np.searchsorted(begins, hits, side="right") - 1).tolist():
            i, at, line = lines[n]
            stop = starts[n + 1] if n + 1 < len(starts) else len(words)
            cursor, open_span, own = 0, None, []
            for k in range(starts[n], stop):
                begin = line.index(words[k], cursor)
                cursor = begin + len(words[k])
                label = int(labels[k])
                kind, inside = (label - 1) // 2, label % 2 == 0
                if label and open_span and inside and open_span[1] == kind:
                    open_span[2] = cursor
                elif label:
                    open_span = [begin, kind, cursor]
                    own.append(open_span)
                else:
                    open_span = None
            for a, kind, b in own:
                whole = line[a:b]
                left, right = len(whole) - len(whole.lstrip(_MARKS)), len(whole) - len(whole.rstrip(_MARKS))
                # An opening bracket that closes inside belongs to the number.
                left -= left > 0 and whole[left - 1] == "(" and ")" in whole[left:]
                a, b = a + left, b - right
                if a < b and _sound(kind, line[a:b]):
                    out[i].append((a + at, kind, b + at))
        return out


def _sound(kind: int, text: str) -> bool:
    """Whether a decoded number can be one: an ip by its range, a card by its check digit, a phone by its length."""
    number = _digits(text)
    match KINDS[kind]:
        case "ip":
            return text.count(".") == 3 and len(number) + 3 == len(text) and _octets(text)
        case "card":
            return 14 <= len(number) <= 19 and luhn(number)
        case "phone":
            return 7 <= len(number) <= 15
    return True


def merged(base: list[tuple], found: list[tuple]) -> list[tuple]:
    """Base spans and those found that overlap none of them, in order; both lists are sorted, and those found do not overlap."""
    out, k, reach = [], 0, 0  # reach: where the base spans passed so far end
    for span in found:
        while k < len(base) and base[k][0] < span[2]:
            reach = max(reach, base[k][2])
            k += 1
        if reach <= span[0]:
            out.append(span)
    return sorted([*base, *out])


def written(spans: list[tuple]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def _decoder(field: Field) -> Decoder:
    mark = hashlib.sha256(field.weights.tobytes() + field.moves.tobytes()).hexdigest()
    return once(("field", mark), lambda: Decoder(field))


#: Characters that are decoded together.
BLOCK = 1 << 20


def _found(decoder: Decoder, texts: list[str]) -> list[list[tuple]]:
    out, block, size = [], [], 0
    for text in texts:
        block.append(text)
        size += len(text)
        if size > BLOCK:
            out += decoder.spans(block)
            block, size = [], 0
    return out + decoder.spans(block)


def _finding(weights: np.ndarray, moves: np.ndarray, cues: frozenset):
    def run(parts):
        decoder = _decoder(Field(weights.astype(float), moves, cues))
        for part in parts:
            texts = [t or "" for t in part.column(1).to_pylist()]
            rows = []
            for text, found in zip(texts, _found(decoder, texts)):
                base = base_spans(text)
                per = [0] * len(BASE)
                for _, k, _ in base:
                    per[k] += 1
                rows.append((*per, written(base), written(merged(base, found))))
            columns = list(zip(*rows)) if rows else [[]] * 6
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(c, pa.int64()) for c in columns[:4]), *(pa.array(c, pa.string()) for c in columns[4:])], ["id", *(f"n_{k}" for k in BASE), "base", "spans"])

    return run


def find(df: DataFrame, field: Field, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, n_email, n_ip, n_card, n_phone, base_spans, spans)`` of every row; spans as ``kind:start:end`` lists in text."""
    kind = df.schema[id_col].dataType.simpleString()
    run = _finding(field.weights.astype(np.float32), field.moves, field.cues)
    return batches(df.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), run, f"id {kind}, n_email long, n_ip long, n_card long, n_phone long, base string, spans string").withColumnsRenamed({"id": id_col, "base": "base_spans"})


def redacted(text: str, spans: list[tuple]) -> str:
    """The text with every span replaced by its kind in brackets; overlapping spans are one, named by the first."""
    out, at = [], 0
    for a, k, b in spans:
        if a >= at:
            out += [text[at:a], f"[{KINDS[k].upper()}]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def _redacting(weights: np.ndarray, moves: np.ndarray, cues: frozenset):
    def run(parts):
        decoder = _decoder(Field(weights.astype(float), moves, cues))
        for part in parts:
            texts = part.column("__text").to_pylist()
            found = _found(decoder, [t or "" for t in texts])
            new = [t if t is None else redacted(t, merged(base_spans(t), s)) for t, s in zip(texts, found)]
            yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(new, pa.string())], part.schema.names)

    return run


def redact(df: DataFrame, field: Field, text_col: str = "text") -> DataFrame:
    """All rows and columns of ``df`` with personal data in ``text_col`` replaced; null texts stay null."""
    run = _redacting(field.weights.astype(np.float32), field.moves, field.cues)
    given = df.withColumn("__text", F.col(text_col)).drop(text_col)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in given.schema)
    return batches(given, run, schema).withColumnRenamed("__text", text_col).select(*df.columns)
