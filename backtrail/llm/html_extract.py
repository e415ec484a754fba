"""Main text of web pages by a recurrent block labeller.

A page becomes the sequence of its leaf blocks: runs of text between block-level tags, inline tags taken out.  Each block is
read as two hashed vectors, of its tag path (names, classes, ids) and of its words, and a few proportions.  A bidirectional LSTM in
numpy reads the whole sequence, so every block is classified in the light of the document around it.  The blocks
classified as main text, whitespace folded, are joined by newlines in page order.

The labeller's weights are trained by :mod:`backtrail.llm.html_training` from pages drawn by rule and kept beside this module.

A page is read in linear time, whatever it holds.  Elements that browsers do not show as text (``HIDDEN``: scripts, styles, ``noscript``,
drawings, embedded objects) are left out with all they hold if they are closed.  One that is never closed hides nothing that
follows it, but a script's or style's own code up to the next tag; so does a comment that is never closed, up to the next ``>``.

Defined results: null, empty and text-free pages give the empty string; text outside any tag is a block too; unclosed and stray
tags are forgiven; equal rows get equal rows; other columns are not read.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter
from pathlib import Path

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from backtrail.llm.common import batches, once

WEIGHTS = Path(__file__).with_name("html_labeller.npz")
PATH_SIZE, WORD_SIZE, PROPORTIONS, MEMO = 96, 32, 7, 200_000

#: Fixed names of the markup language.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr del br img input".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HIDDEN = frozenset("script style noscript template svg iframe object canvas math".split())
CODE = frozenset(["script", "style"])
#: An opening tag of the second set ends an open element of the first.
IMPLIED = {"p": frozenset("p div ul ol dl table form section article aside nav header footer main h1 h2 h3 h4 h5 h6 blockquote pre hr address fieldset figure details".split()), "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "td": frozenset("td th tr tbody".split()), "th": frozenset("td th tr tbody".split()), "tr": frozenset("tr tbody".split()), "option": frozenset(["option"])}

_NAME = re.compile(r"[a-zA-Z][a-zA-Z0-9:-]*")
_NAMES = re.compile(r"\b(?:class|id|role|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_WORD = re.compile(r"\w+")
_STOP = re.compile(r"[>\"']")


class Node:
    """An open element; its path to the root is shared with its neighbours."""

    __slots__ = ("parent", "name", "names", "vector")

    def __init__(self, parent, name, names):
        self.parent, self.name, self.names, self.vector = parent, name, names, None


class Block:
    __slots__ = ("node", "parts", "linked", "text")

    def __init__(self, node):
        self.node, self.parts, self.linked, self.text = node, [], 0, ""


class _Scanner:
    """Finds the ends of markup; what is known not to follow is never looked for again, so a page is read in linear time."""

    def __init__(self, page: str):
        self.page, self.none, self.quotes, self.last = page, set(), True, page.rfind(">")

    def after(self, sign: str, at: int) -> int:
        """Place behind the next ``sign``, or -1."""
        if sign in self.none:
            return -1
        found = self.page.find(sign, at)
        if found < 0:
            self.none.add(sign)
        return found + len(sign) if found >= 0 else -1

    def closed(self, name: str, at: int) -> int:
        """Place behind the closing tag of a hidden element, or -1."""
        if name in self.none:
            return -1
        found = re.compile(rf"</{name}\b", re.I).search(self.page, at)
        if found is None:
            self.none.add(name)
            return -1
        return self.after(">", found.end())

    def tag_end(self, at: int) -> int:
        """Place of the tag's end; signs in quotes do not end it, unless a quotation never closes."""
        k = at
        while self.quotes:
            found = _STOP.search(self.page, k)
            if found is None:
                break
            if found[0] == ">":
                return found.start()
            k = self.page.find(found[0], found.end()) + 1
            if not k:
                break
        self.quotes = False
        return self.page.find(">", at)


def blocks(page: str) -> list[Block]:
    """Leaf blocks with text, in page order."""
    out: list[Block] = []
    node, opened = None, Counter()
    current, at, links = None, 0, 0
    scan, end = _Scanner(page), len(page)

    def said(text: str) -> None:
        nonlocal current
        if text:
            if current is None:
                current = Block(node)
                out.append(current)
            current.parts.append(text)
            if links:
                current.linked += len(text)

    def close() -> None:
        nonlocal node
        opened[node.name] -= 1
        node = node.parent

    look = 0  # from where the next tag is looked for; what lies between ``at`` and it is text
    while True:
        begin = page.find("<", look) if look <= scan.last else -1
        if begin < 0 or begin > scan.last:
            said(page[at:end])
            break
        if page.startswith(("<!", "<?"), begin):
            said(page[at:begin])
            stop = scan.after("-->", begin + 4) if page.startswith("<!--", begin) else scan.after("]]>", begin) if page.startswith("<![CDATA[", begin) else -1
            at = look = stop if stop > 0 else page.find(">", begin) + 1
            continue
        closing = page.startswith("/", begin + 1)
        found = _NAME.match(page, begin + 1 + closing)
        if found is None:
            look = begin + 1
            continue
        stop = scan.tag_end(found.end())
        said(page[at:begin])
        at = look = stop + 1
        name, rest = found[0].lower(), page[found.end() : stop]
        if name in HIDDEN:
            if not closing and not rest.endswith("/"):
                stop = scan.closed(name, at)
                if stop < 0 and name in CODE:  # never closed: its code ends before the next tag
                    stop = page.find("<", at)
                    stop = end if stop < 0 else stop
                if stop >= 0:
                    at = look = stop
            continue
        if name == "br":
            said(" ")
            continue
        if name == "a":
            links = max(0, links + (-1 if closing else 1))
        if name in INLINE:
            continue
        current = None
        if closing:
            if opened[name] > 0:
                while node.name != name:
                    close()
                close()
            links = 0
        else:
            while node is not None and name in IMPLIED.get(node.name, ()):
                close()
            if name not in VOID and not rest.endswith("/"):
                names = [name]
                for given in _NAMES.findall(rest):
                    names += [f".{n}" for n in re.split(r"[\s_\-]+", "".join(given).lower()) if n]
                node = Node(node, name, tuple(names))
                opened[name] += 1
    kept = []
    for block in out:
        block.text = " ".join(html.unescape("".join(block.parts)).split())
        if block.text:
            kept.append(block)
    return kept


# --- what the labeller reads -------------------------------------------------------------------------------------------


def _signed(name: str, size: int, seed: int) -> tuple[int, float]:
    h = xxhash.xxh64_intdigest(name.encode(), seed)
    return (h >> 8) % size, 1.0 if h & 1 else -1.0


class Reader:
    """Vectors of blocks; hashes are remembered within a bound."""

    def __init__(self):
        self.paths, self.words = {}, {}

    def _names(self, names: tuple) -> tuple[np.ndarray, np.ndarray]:
        """What an element adds to the paths through it, and to those that end with it."""
        if names not in self.paths:
            if len(self.paths) > MEMO // 20:
                self.paths.clear()
            vectors = np.zeros((2, PATH_SIZE), np.float32)
            for row, name in [*((0, n) for n in names), (1, f"last {names[-1]}")]:
                for seed in (3, 4):
                    k, sign = _signed(name, PATH_SIZE, seed)
                    vectors[row, k] += sign
            self.paths[names] = vectors[0], vectors[1]
        return self.paths[names]

    def path(self, node: Node | None) -> np.ndarray:
        """Sum over the path's names, the last one twice; shared parts are summed once."""
        fresh = []
        here = node
        while here is not None and here.vector is None:
            fresh.append(here)
            here = here.parent
        for n in reversed(fresh):
            own = self._names(n.names)[0]
            n.vector = own if n.parent is None else n.parent.vector + own
        return np.zeros(PATH_SIZE, np.float32) if node is None else node.vector + self._names(node.names)[1]

    def word(self, word: str) -> tuple[int, float]:
        if word not in self.words:
            if len(self.words) > MEMO:
                self.words.clear()
            self.words[word] = _signed(word, WORD_SIZE, 5)
        return self.words[word]

    def page(self, found: list[Block]) -> np.ndarray:
        out = np.zeros((len(found), PATH_SIZE + WORD_SIZE + PROPORTIONS), np.float32)
        for i, block in enumerate(found):
            text = block.text
            words = _WORD.findall(text.lower())
            out[i, :PATH_SIZE] = self.path(block.node)
            if words:
                pairs = [self.word(w) for w in words]
                at, signs = zip(*pairs)
                bag = np.bincount(at, signs, WORD_SIZE)
                out[i, PATH_SIZE : PATH_SIZE + WORD_SIZE] = bag / max(1.0, math.sqrt(float(bag @ bag)))
            n = len(text)
            out[i, PATH_SIZE + WORD_SIZE :] = (
                math.log1p(n) / 6, min(1.0, block.linked / n), 1.0 if text[-1] in ".!?:;\"'" else 0.0, min(1.0, 20 * sum(map(text.count, ".,;")) / n),
                i / len(found), 1 / (1 + i), 1 / (len(found) - i),
            )
        return out


# --- the network -------------------------------------------------------------------------------------------------------


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def reversal(lengths: np.ndarray, longest: int) -> np.ndarray:
    """Index of each row's steps in reverse, padding left in place."""
    steps = np.arange(longest)[None, :]
    return np.where(steps < lengths[:, None], lengths[:, None] - 1 - steps, steps)


class Labeller:
    """A bidirectional LSTM over block vectors with a logistic output for each block."""

    def __init__(self, parameters: dict[str, np.ndarray]):
        self.p = {k: v.astype(np.float32) for k, v in parameters.items()}

    @classmethod
    def load(cls, path=WEIGHTS) -> Labeller:
        with np.load(path) as stored:
            return cls({k: stored[k] for k in stored.files})

    def _pass(self, x: np.ndarray, side: str) -> np.ndarray:
        wx, wh, b = (self.p[f"{side}_{k}"] for k in ("x", "h", "b"))
        rows, steps, _ = x.shape
        size = wh.shape[0]
        given = x @ wx + b
        h, c = np.zeros((rows, size), np.float32), np.zeros((rows, size), np.float32)
        out = np.zeros((rows, steps, size), np.float32)
        for t in range(steps):
            z = given[:, t] + h @ wh
            gates = _sigmoid(z[:, : 3 * size])
            c = gates[:, size : 2 * size] * c + gates[:, :size] * np.tanh(z[:, 3 * size :])
            h = gates[:, 2 * size :] * np.tanh(c)
            out[:, t] = h
        return out

    def scores(self, pages: list[np.ndarray]) -> list[np.ndarray]:
        """Log-odds of being main text for every block of every page; pages of like length run side by side."""
        out: list = [None] * len(pages)
        order = sorted((i for i in range(len(pages)) if len(pages[i])), key=lambda i: len(pages[i]))
        at = 0
        while at < len(order):
            stop = at + 1
            while stop < len(order) and stop - at < 256 and len(pages[order[stop]]) <= 1.25 * len(pages[order[at]]) + 2:
                stop += 1
            group = order[at:stop]
            lengths = np.array([len(pages[i]) for i in group])
            x = np.zeros((len(group), int(lengths.max()), pages[group[0]].shape[1]), np.float32)
            for row, i in enumerate(group):
                x[row, : lengths[row]] = pages[i]
            back = reversal(lengths, x.shape[1])
            rows = np.arange(len(group))[:, None]
            both = np.concatenate([self._pass(x, "ahead"), self._pass(x[rows, back], "back")[rows, back]], 2)
            found = both @ self.p["out"] + self.p["bias"]
            for row, i in enumerate(group):
                out[i] = found[row, : lengths[row]]
            at = stop
        return [np.zeros(0, np.float32) if s is None else s for s in out]


def extract_all(pages: list[str | None], labeller: Labeller, reader: Reader) -> list[str]:
    found = [blocks(p) if p else [] for p in pages]
    scores = labeller.scores([reader.page(f) for f in found])
    return ["\n".join(b.text for b, s in zip(f, score) if s > 0) for f, score in zip(found, scores)]


def _extracting(parameters: dict[str, np.ndarray], mark: str):
    def run(parts):
        labeller, reader = once(("html", mark), lambda: (Labeller(parameters), Reader()))
        for part in parts:
            pages, texts = part.column("html").to_pylist(), []
            for i in range(0, len(pages), 256):
                texts += extract_all(pages[i : i + 256], labeller, reader)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string())], ["id", "url", "text"])

    return run


def extract(df: DataFrame, labeller: Labeller | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``(id_col, url_col, text, n_chars)`` of every page."""
    labeller = labeller or Labeller.load()
    mark = xxhash.xxh64_hexdigest(b"".join(labeller.p[k].tobytes() for k in sorted(labeller.p)))
    kinds = {c: df.schema[c].dataType.simpleString() for c in (id_col, url_col)}
    given = df.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    out = batches(given, _extracting({k: v.astype(np.float16) for k, v in labeller.p.items()}, mark), f"id {kinds[id_col]}, url {kinds[url_col]}, text string")
    return out.select(F.col("id").alias(id_col), F.col("url").alias(url_col), "text", F.length("text").cast("long").alias("n_chars"))
