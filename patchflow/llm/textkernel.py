"""Vectorised word and window hashing over groups of texts.

Texts of a group are joined by a line feed, which is white space and a line end, so
that neither words nor lines cross documents.  Hashes are polynomial prefix
sums modulo 2**64 over random byte values, finished by a 64-bit mixer; a hash of any
run of bytes or words then costs two lookups.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
SPACES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
IS_SPACE = np.zeros(256, bool)
IS_SPACE[list(SPACES)] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values (multiply and shift)."""
    x = x.astype(U, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


BYTE = mix(np.arange(1, 257, dtype=U) * U(0x9E3779B97F4A7C15))
LOWER_BYTE = BYTE.copy()
LOWER_BYTE[65:91] = BYTE[97:123]


class Powers:
    """Powers of an odd base and of its inverse; kept up to ``keep`` entries."""

    def __init__(self, base: int, keep: int = 1 << 21):
        self.base, self.inverse, self.keep = base, pow(base, -1, 1 << 64), keep
        self.up = self.down = np.ones(1, U)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > len(self.up):
            size = max(n, min(2 * len(self.up), self.keep))
            made = []
            for b in (self.base, self.inverse):
                p = np.full(size, U(b))
                p[0] = 1
                made.append(np.multiply.accumulate(p))
            if size > self.keep:
                return made[0][:n], made[1][:n]
            self.up, self.down = made
        return self.up[:n], self.down[:n]


BYTES_POW = Powers(0xD6E8FEB86659FD93)
WORDS_POW = Powers(0xA0761D6478BD642F)


def prefix(values: np.ndarray, powers: Powers) -> np.ndarray:
    out = np.zeros(len(values) + 1, U)
    if len(values):
        np.cumsum(values * powers.get(len(values))[0], out=out[1:])
    return out


def run_hash(sums: np.ndarray, start: np.ndarray, end: np.ndarray, powers: Powers) -> np.ndarray:
    """Hash of the values from start to end (exclusive), wherever they stand."""
    return mix((sums[end] - sums[start]) * powers.get(len(sums))[1][start])


class Words:
    """The words of a group of texts: bounds, document and hash of each."""

    def __init__(self, texts: list[bytes], lower: bool = False):
        self.n = len(texts)
        self.buffer = np.frombuffer(b"\n".join([*texts, b""]), np.uint8)
        lengths = np.fromiter(map(len, texts), np.int64, self.n)
        self.doc_end = np.cumsum(lengths + 1) - 1
        self.doc_start = self.doc_end - lengths
        inside = ~IS_SPACE[self.buffer]
        edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
        if len(inside) and inside[0]:
            edge = np.concatenate([[0], edge])
        self.start, self.end = edge[0::2], edge[1::2]
        self.inside = inside
        self.doc = np.searchsorted(self.doc_end, self.start)
        self.count = np.bincount(self.doc, minlength=self.n)
        self.first = np.concatenate([[0], np.cumsum(self.count)])
        self.sums = prefix((LOWER_BYTE if lower else BYTE)[self.buffer], BYTES_POW)
        self.hash = run_hash(self.sums, self.start, self.end, BYTES_POW)
        self._words = None

    def word_sums(self) -> np.ndarray:
        if self._words is None:
            self._words = prefix(self.hash, WORDS_POW)
        return self._words

    def windows(self, w: int) -> tuple[np.ndarray, np.ndarray]:
        """First word and hash of every run of w words of one document."""
        if len(self.hash) < w:
            return np.zeros(0, np.int64), np.zeros(0, U)
        at = np.flatnonzero(self.doc[w - 1 :] == self.doc[: len(self.doc) - w + 1])
        return at, run_hash(self.word_sums(), at, at + w, WORDS_POW)

    def per_doc(self, flags: np.ndarray) -> np.ndarray:
        """Number of set byte flags in each text."""
        total = np.concatenate([[0], np.cumsum(flags)])
        return total[self.doc_end] - total[self.doc_start]


def with_doc(hashes: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Hashes that differ between documents."""
    return mix(hashes ^ mix(doc.astype(U) + U(1)))
