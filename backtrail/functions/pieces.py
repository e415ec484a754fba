"""Which of many given texts stand in other texts, by window hashes over the bytes of Arrow batches.

A window's hash is the difference of two prefix sums of byte codes times powers of an odd number, divided by the power at its start,
modulo 2**64: one subtraction and one product at every place, whatever the window's length.  A given text is looked for by its
first 1, 2, 4, 8, 16 or 32 bytes, or as many as a large share of the given texts have in all (the largest that it has), then by all of them;
what is found is compared byte by byte, so that a hash alone never decides.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

#: Places looked at together.
BLOCK = 1 << 17
#: Bytes of the longest beginning that texts are looked for by.
BEGIN = 32
#: A length that more than one in so many texts have is a beginning of its own: fewer places pass the first look.
COMMON = 16

#: Odd numbers: the base of the powers; two that spread hashes over marks; one that lengths are mixed in by.
_ODD, _SPREAD, _AGAIN, _LENGTH = 0x9E3779B97F4A7C15, np.uint64(0xD6E8FEB86659FD93), np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC2B2AE3D27D4EB4F)


def _bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of an array of texts, and where each begins and the last one ends; nulls are empty."""
    texts = texts.cast(pa.large_string()).fill_null("")
    places = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(texts.buffers()[2], np.uint8) if texts.buffers()[2] is not None and texts.buffers()[2].size else np.zeros(0, np.uint8)
    return data[places[0] : places[-1]], places - places[0]


class _Sums:
    def __init__(self, longest: int, seed: int):
        codes = np.random.default_rng(seed).integers(0, 1 << 64, 256, np.uint64)
        powers = lambda x: np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(longest, x, np.uint64))])
        self.codes, self.up, self.down = codes, powers(_ODD), powers(pow(_ODD, -1, 1 << 64))

    def of(self, data: np.ndarray) -> np.ndarray:
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self.codes[data] * self.up[: len(data)], out=out[1:])
        return out

    def windows(self, sums: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
        return (sums[at + n] - sums[at]) * self.down[at]


def _runs(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """``first[i], first[i] + 1, …``, ``count[i]`` of them, one after the other."""
    return np.repeat(first - (np.cumsum(count) - count), count) + np.arange(count.sum())


def _looked_up(keys: np.ndarray, found: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places in sorted ``keys`` of what is found, and which are there."""
    at = np.minimum(np.searchsorted(keys, found), len(keys) - 1)
    return at, keys[at] == found


class Pieces:
    """Distinct texts, none of them empty, to be looked for."""

    def __init__(self, texts: pa.Array):
        self.data, self.places = _bytes(texts)
        self.size = np.diff(self.places)
        self.longest = int(self.size.max(initial=0))
        seed = 0
        while not self._hashed(seed):  # two texts of one hash: other codes
            seed += 1

    def _hashed(self, seed: int) -> bool:
        self.seed = seed
        sizes, count = np.unique(self.size, return_counts=True)
        begins = np.union1d(1 << np.arange(BEGIN.bit_length()), sizes[count > len(self.size) / COMMON])
        begin = begins[np.searchsorted(begins, self.size, "right") - 1]
        sums = _Sums(BLOCK + self.longest, seed)
        whole, start, i = np.zeros(len(self.size), np.uint64), np.zeros(len(self.size), np.uint64), 0
        while i < len(self.size):
            j = max(i + 1, int(np.searchsorted(self.places, self.places[i] + BLOCK, "right")) - 1)
            at = self.places[i:j] - self.places[i]
            of = sums.of(self.data[self.places[i] : self.places[j]])
            whole[i:j], start[i:j] = sums.windows(of, at, self.size[i:j]), sums.windows(of, at, begin[i:j])
            i = j
        whole ^= self.size.astype(np.uint64) * _LENGTH
        self.order = np.argsort(whole)
        self.whole = whole[self.order]
        self.begins = {}
        for g in np.unique(begin):
            own = begin == g
            pairs = np.unique(np.rec.fromarrays([start[own], self.size[own]], names="h,n"))
            keys, first = np.unique(pairs["h"], return_index=True)
            self.begins[int(g)] = keys, np.append(first, len(pairs)), np.ascontiguousarray(pairs["n"])
        return bool((self.whole[1:] != self.whole[:-1]).all())

    def ready(self) -> Pieces:
        """With powers and marks of the beginnings, which take less time to make than to send."""
        if "sums" not in vars(self):
            self.sums, self.marks = _Sums(BLOCK + self.longest, self.seed), {}
            for g, (keys, _, _) in self.begins.items():
                shift = np.uint64(64 - max(16, min(24, int(len(keys) * 16).bit_length())))
                self.marks[g] = np.zeros(1 << (64 - int(shift)), bool), shift
                self.marks[g][0][(keys * _SPREAD) >> shift] = True
                self.marks[g][0][(keys * _AGAIN) >> shift] = True
        return self

    def __getstate__(self):
        return {k: v for k, v in vars(self).items() if k not in ("sums", "marks")}

    def _same(self, part: np.ndarray, at: np.ndarray, item: np.ndarray) -> np.ndarray:
        out, n = np.zeros(len(at), bool), self.size[item]
        order = np.argsort(n, kind="stable")
        edges = np.flatnonzero(np.diff(n[order], prepend=-1, append=-1))
        for a, b in zip(edges[:-1], edges[1:]):
            length = int(n[order[a]])
            x, y = (np.lib.stride_tricks.sliding_window_view(z, length) for z in (part, self.data))
            step = max(1, (1 << 22) // length)
            for k in range(a, b, step):
                own = order[k : min(k + step, b)]
                out[own] = (x[at[own]] == y[self.places[item[own]]]).all(axis=1)
        return out

    def within(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """``(row, piece)`` for every piece that stands in a row's text, each once, in order of rows."""
        data, places = _bytes(texts)
        ends, many, found = places[1:], max(1, len(self.size)), []
        sums = self.ready().sums
        for b in range(0, len(data) if self.longest else 0, BLOCK):
            part = data[b : b + BLOCK + self.longest]
            of = sums.of(part)
            for g, (keys, first, lengths) in self.begins.items():
                known, shift = self.marks[g]
                if (m := min(BLOCK, len(part) - g + 1)) <= 0:
                    continue
                hashes = (of[g : g + m] - of[:m]) * sums.down[:m]
                at = np.flatnonzero(known[(hashes * _SPREAD) >> shift])
                at = at[known[(hashes[at] * _AGAIN) >> shift]]
                key, hit = _looked_up(keys, hashes[at])
                at, key = at[hit], key[hit]
                count = first[key + 1] - first[key]
                at, n = np.repeat(at, count), lengths[_runs(first[key], count)]
                row = np.searchsorted(ends, at + b, "right")
                inside = at + b + n <= ends[row]
                at, n, row = at[inside], n[inside], row[inside]
                place, hit = _looked_up(self.whole, sums.windows(of, at, n) ^ (n.astype(np.uint64) * _LENGTH))
                at, row, item, n = at[hit], row[hit], self.order[place[hit]], n[hit]
                same = (self.size[item] == n) & (at + self.size[item] <= len(part))
                at, row, item = at[same], row[same], item[same]
                same = self._same(part, at, item)
                found.append(np.unique(row[same] * many + item[same]))
        keys = np.unique(np.concatenate(found)) if found else np.zeros(0, np.int64)
        return keys // many, keys % many
