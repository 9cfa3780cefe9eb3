"""Words of many texts at once, found and hashed with numpy on their UTF-8 bytes.

A word class is a set of bytes in which every byte from 0x80 on is a word byte, so a word never splits a code point.
Words get a 64-bit polynomial hash (modulo 2**64, odd base) from prefix sums; what matters is checked on the bytes."""

from __future__ import annotations

import numpy as np

BASE = 0x9E3779B97F4A7C15 | 1
_POWERS: dict[str, np.ndarray] = {}
#: Bytes hashed at one go.
PIECE = 1 << 18


def lower_table() -> bytes:
    """For bytes.translate: A-Z to a-z."""
    return bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def alnum_class() -> np.ndarray:
    """0-9, a-z and every byte from 0x80 on: the class of [^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F] in lower-cased text."""
    t = np.zeros(256, bool)
    t[0x30:0x3A] = t[0x61:0x7B] = t[0x80:] = True
    return t


def nonspace_class() -> np.ndarray:
    """All but the white space bytes 0x20 and 0x09 to 0x0D."""
    t = np.ones(256, bool)
    t[0x20] = False
    t[0x09:0x0E] = False
    return t


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64."""
    if "p" not in _POWERS or len(_POWERS["p"]) < n:
        n = max(n, PIECE + 1)
        with np.errstate(over="ignore"):
            for name, base in (("p", BASE), ("q", pow(BASE, -1, 1 << 64))):
                step = np.full(n, base, np.uint64)
                step[0] = 1
                _POWERS[name] = np.multiply.accumulate(step)
    return _POWERS["p"], _POWERS["q"]


def word_bounds(buf: np.ndarray, klass: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end offsets of the maximal runs of word bytes."""
    inside = np.zeros(len(buf) + 2, np.int8)
    inside[1:-1] = klass[buf]
    step = np.diff(inside)
    return np.flatnonzero(step == 1), np.flatnonzero(step == -1)


def word_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each word, in pieces so that the tables stay small."""
    out = np.empty(len(starts), np.uint64)
    at = 0
    while at < len(starts):
        low = int(starts[at])
        to = max(at + 1, int(np.searchsorted(ends, low + PIECE, side="right")))
        n = int(ends[to - 1]) - low
        p, q = powers(n + 1)
        with np.errstate(over="ignore"):
            pre = np.zeros(n + 1, np.uint64)
            np.cumsum((buf[low : low + n].astype(np.uint64) + np.uint64(1)) * p[:n], out=pre[1:])
            s, e = starts[at:to] - low, ends[at:to] - low
            h = (pre[e] - pre[s]) * q[s]
            h ^= h >> np.uint64(29)
            out[at:to] = h * np.uint64(0xBF58476D1CE4E5B9)
        at = to
    return out


class Words:
    """The words of a list of texts (lower-cased A-Z).

    buf: all texts, each followed by a line feed; doc: number of words before each text (one more than texts);
    start, end: offsets in buf; hashes: one for each word."""

    def __init__(self, texts: list[bytes], klass: np.ndarray, hashed: bool = True):
        self.raw = (b"\n".join(texts) + b"\n").translate(lower_table())
        self.buf = np.frombuffer(self.raw, np.uint8)
        self.offsets = np.zeros(len(texts) + 1, np.int64)
        np.cumsum([len(t) + 1 for t in texts], out=self.offsets[1:])
        self.start, self.end = word_bounds(self.buf, klass)
        self.doc = np.searchsorted(self.start, self.offsets)
        self.hashes = word_hashes(self.buf, self.start, self.end) if hashed else None

    def count(self) -> np.ndarray:
        return np.diff(self.doc)

    def word(self, i: int) -> bytes:
        return self.raw[self.start[i] : self.end[i]]

    def span(self, i: int, n: int) -> bytes:
        """n words from word i on, joined by spaces."""
        return b" ".join(self.raw[s:e] for s, e in zip(self.start[i : i + n], self.end[i : i + n], strict=True))

    def window_hashes(self, n: int) -> np.ndarray:
        """A hash of each n consecutive words, across texts too: see inside()."""
        h, m = self.hashes, len(self.hashes) - n + 1
        if m <= 0:
            return np.zeros(0, np.uint64)
        out = np.zeros(m, np.uint64)
        with np.errstate(over="ignore"):
            for j in range(n):
                out *= np.uint64(BASE)
                out += h[j : j + m]
            out ^= out >> np.uint64(31)
        return out

    def inside(self, at: np.ndarray, n: int) -> np.ndarray:
        """Which windows of n words that start at the given words lie in one text."""
        text = np.searchsorted(self.doc, at, side="right") - 1
        return at + n <= self.doc[text + 1]
