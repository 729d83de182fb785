"""Vectorised word hashing on the UTF-8 bytes of a batch of texts.

One pass of NumPy over the joined bytes gives every word's start, end and 64-bit hash; no Python loop over words.
Words are runs of bytes other than ASCII white space; A-Z count as a-z.
"""

from __future__ import annotations

import numpy as np

_BASE = np.uint64(0x9E3779B97F4A7C15)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


#: Everything in ASCII but letters and digits, for tokens without punctuation.
PUNCTUATION = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser with full avalanche over uint64."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE = mix64(np.arange(1, 257, dtype=np.uint64) * _BASE)[_LOWER]


class Words:
    """Words of a batch: ``start``, ``end`` (byte offsets in ``data``), ``hash``, and ``first[i]:first[i+1]`` of text i."""

    def __init__(self, texts: list, gap: np.ndarray = _SPACE):
        raw = [b"" if t is None else t.encode("utf-8", "surrogatepass") for t in texts]
        self.data = np.frombuffer(b"\n".join(raw) + b"\n", dtype=np.uint8)
        self.offset = np.zeros(len(raw) + 1, dtype=np.int64)
        np.cumsum([len(x) + 1 for x in raw], out=self.offset[1:])
        letter = np.zeros(len(self.data) + 1, dtype=bool)
        np.logical_not(gap[self.data], out=letter[1:])
        turn = np.flatnonzero(letter[1:] != letter[:-1])
        self.start, self.end = turn[0::2], turn[1::2]
        self.first = np.searchsorted(self.start, self.offset)
        self.hash = self._hash()

    def _hash(self) -> np.ndarray:
        """Polynomial hash of each word over per-byte random values, position counted from the word's start."""
        n = self.end - self.start
        out = np.zeros(len(n), dtype=np.uint64)
        order = np.argsort(-n, kind="stable")
        start, length = self.start[order], n[order]
        acc = np.zeros(len(n), dtype=np.uint64)
        live, k = len(n), 0
        while live and k < 48:
            live = int(np.searchsorted(-length, -k, side="left"))
            if not live:
                break
            acc[:live] = acc[:live] * _BASE + _BYTE[self.data[start[:live] + k]]
            k += 1
        for i in range(live if k >= 48 else 0):
            if length[i] <= 48:
                break
            piece = _BYTE[self.data[start[i] + 48 : start[i] + length[i]]]
            with np.errstate(over="ignore"):
                acc[i] = acc[i] * _BASE + self._fold(piece)
        out[order] = mix64(acc + length.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        return out

    @staticmethod
    def _fold(piece: np.ndarray) -> np.uint64:
        power = np.cumprod(np.full(len(piece), _BASE, dtype=np.uint64))
        return (piece * power).sum(dtype=np.uint64)

    def prefix_hash(self, size: int) -> np.ndarray:
        """Hash of each word's first ``size`` bytes (of all, if it has fewer)."""
        n = np.minimum(self.end - self.start, size)
        acc = n.astype(np.uint64)
        for k in range(size):
            at = np.minimum(self.start + k, len(self.data) - 1)
            acc = np.where(k < n, acc * _BASE + _BYTE[self.data[at]], acc)
        return mix64(acc)

    def chars_before(self) -> np.ndarray:
        """Code points before each byte offset of ``data``."""
        at = np.zeros(len(self.data) + 1, dtype=np.int64)
        np.cumsum((self.data & 0xC0) != 0x80, out=at[1:])
        return at


def shingles(words: Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all texts, and ``first`` as in ``Words``; fewer words make one shingle."""
    h, first = words.hash, words.first
    counts = np.diff(first)
    if len(h) == 0:
        return np.zeros(0, np.uint64), np.zeros(len(counts) + 1, np.int64)
    with np.errstate(over="ignore"):
        run = np.zeros(max(0, len(h) - size + 1), dtype=np.uint64)
        for j in range(size):
            run = mix64(run * _BASE + h[j : j + len(run)]) if len(run) else run
    out, bounds = [], np.zeros(len(counts) + 1, dtype=np.int64)
    for i, n in enumerate(counts.tolist()):
        a = first[i]
        if n >= size:
            own = np.unique(run[a : a + n - size + 1])
        elif n:
            acc = np.uint64(n)
            with np.errstate(over="ignore"):
                for x in h[a : a + n]:
                    acc = mix64(np.array([acc * _BASE + x]))[0]
            own = np.array([acc], dtype=np.uint64)
        else:
            own = np.zeros(0, dtype=np.uint64)
        out.append(own)
        bounds[i + 1] = bounds[i] + len(own)
    return (np.concatenate(out) if out else np.zeros(0, np.uint64)), bounds


def slices(texts: list, most: int = 1 << 20):
    """(from, to) so that each slice has about ``most`` characters or a single longer text."""
    a = size = 0
    for i, t in enumerate(texts):
        n = len(t) if t else 0
        if size and size + n > most:
            yield a, i
            a, size = i, 0
        size += n + 1
    if a < len(texts):
        yield a, len(texts)
