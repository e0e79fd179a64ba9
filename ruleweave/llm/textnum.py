"""Texts as numpy arrays: words, 64-bit word hashes and rolling window hashes, without a Python loop over words.

A word is a maximal run of bytes other than the ASCII blanks 0x09-0x0D and 0x20, as bytes.split() has it.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_CHUNK = 1 << 20
_R = U(0x9E3779B97F4A7C15)
_R_INV = U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (shift, multiply, shift)."""
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    x = x ^ (x >> U(32))
    x = x * U(0xD6E8FEB86659FD93)
    return x ^ (x >> U(32))


def _bytes_table(seed: int) -> np.ndarray:
    return mix(np.arange(1, 257, dtype=U) * _R + U(seed))


_TABLES: dict = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _TABLES.get("pow")
    if have is None or len(have[0]) < n:
        size = max(n, _CHUNK + 1)
        up, down = np.full(size, _R, U), np.full(size, _R_INV, U)
        up[0] = down[0] = U(1)
        have = np.multiply.accumulate(up), np.multiply.accumulate(down)
        if size <= 2 * _CHUNK:
            _TABLES["pow"] = have
    return have


class Words:
    """The words of a list of texts: starts and ends in buf, the number of the text each word is in, and how many words each text has."""

    def __init__(self, texts: list[bytes]):
        self.buf = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
        sizes = np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts))
        offsets = np.concatenate([[0], np.cumsum(sizes)])
        blank = _BLANK[self.buf]
        before = np.empty_like(blank)
        before[:1], before[1:] = True, blank[:-1]
        self.starts = np.flatnonzero(before & ~blank)
        self.ends = np.flatnonzero(blank & ~before)
        self.first = np.searchsorted(self.starts, offsets)
        self.counts = np.diff(self.first)
        self.text_of = np.repeat(np.arange(len(texts)), self.counts)

    def hashes(self, seed: int = 0) -> np.ndarray:
        """One hash a word: a polynomial over its bytes, from prefix sums taken chunk by chunk."""
        table = _TABLES.setdefault(("bytes", seed), _bytes_table(seed))
        out, n, i = np.empty(len(self.starts), U), len(self.starts), 0
        while i < n:
            base = self.starts[i]
            j = max(i + 1, int(np.searchsorted(self.ends, base + _CHUNK, "right")))
            up, down = _powers(int(self.ends[j - 1] - base) + 1)
            sums = np.zeros(self.ends[j - 1] - base + 1, U)
            np.cumsum(table[self.buf[base : self.ends[j - 1]]] * up[: len(sums) - 1], out=sums[1:])
            lo, hi = self.starts[i:j] - base, self.ends[i:j] - base
            out[i:j] = (sums[hi] - sums[lo]) * down[lo] + (hi - lo).astype(U)
            i = j
        return mix(out)

    def windows(self, word_hashes: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """First words of all windows of n words inside one text, and the windows' hashes."""
        if len(word_hashes) < n:
            return np.empty(0, np.int64), np.empty(0, U)
        last = len(word_hashes) - n + 1
        at = np.flatnonzero(self.text_of[:last] == self.text_of[n - 1 :])
        h = word_hashes[:last].copy()
        for k in range(1, n):
            h *= _R
            h += word_hashes[k : last + k]
        return at, mix(h[at] if len(at) < last else h)


def encoded(texts) -> list[bytes]:
    """UTF-8 of each text, null as empty."""
    return [b"" if t is None else t.encode() for t in texts]
