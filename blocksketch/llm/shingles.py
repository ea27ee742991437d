"""Word shingles of many texts at once: bytes in NumPy arrays, constant-time window hashes, no Python loop over words."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from .common import U64, Windows, mix, seeds

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_WORD = seeds("word", 16)
_SET = seeds("set", 2)


def chunks(texts, most: int = 1 << 19, rows: int = 1 << 14) -> Iterator[tuple[int, list[bytes]]]:
    """The texts' bytes (null: empty) in runs of about `most` bytes and up to `rows` texts, each with the index of its first text."""
    first, held, size = 0, [], 0
    for i, t in enumerate(texts):
        b = t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b""
        held.append(b)
        size += len(b)
        if size >= most or len(held) >= rows:
            yield first, held
            first, held, size = i + 1, [], 0
    if held:
        yield first, held


class Words:
    """Words of a run of texts: start, end (bytes in the joined text), hash, and the index of the text of each."""

    def __init__(self, texts: list[bytes], lower: bool = True):
        self.n = len(texts)
        data = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
        self.data = LOWER[data] if lower else data
        self.offset = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])]).astype(np.int64)
        edge = np.diff(np.concatenate([[True], SPACE[self.data]]).astype(np.int8))
        self.start, self.end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
        self.doc = np.searchsorted(self.offset, self.start, "right") - 1
        self.windows = Windows(self.data)
        self.hash = self.windows.hash(self.start, self.end)
        self.count = np.bincount(self.doc, minlength=self.n)

    def runs(self, width: int) -> tuple[np.ndarray, np.ndarray]:
        """The hash of each run of `width` words within a text, and the index of its first word."""
        m = len(self.hash) - width + 1
        if m <= 0:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        h = np.zeros(m, np.uint64)
        for k in range(width):
            h += self.hash[k : k + m] * _WORD[k]
        at = np.flatnonzero(self.doc[:m] == self.doc[width - 1 :])
        return mix(h[at]), at

    def sets(self, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
        """Distinct shingles: hashes ascending within each text, and the index of the text. A text of fewer words has one, of all of them."""
        h, at = self.runs(width)
        doc = self.doc[at]
        few = np.flatnonzero((self.count > 0) & (self.count < width))
        if len(few):
            first = np.searchsorted(self.doc, few)
            whole = np.zeros(len(few), np.uint64)
            for k in range(width - 1):
                has = self.count[few] > k
                whole[has] += self.hash[first[has] + k] * _WORD[k]
            h = np.concatenate([h, mix(whole + U64(1) + self.count[few].astype(np.uint64))])
            doc = np.concatenate([doc, few])
        order = np.lexsort((h, doc))
        h, doc = h[order], doc[order]
        if len(h):
            new = np.concatenate([[True], (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])])
            h, doc = h[new], doc[new]
        return h, doc


def set_hash(h: np.ndarray, doc: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit sums that identify each text's set."""
    out = []
    for k in range(2):
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(h * _SET[k]))])
        ends = np.searchsorted(doc, np.arange(n + 1))
        out.append((total[ends[1:]] - total[ends[:-1]]).view(np.int64))
    return out[0], out[1]


def sketches(h: np.ndarray, doc: np.ndarray, n: int, size: int) -> np.ndarray:
    """Fast similarity sketches, n x size (a power of two): in each of the first `size` rounds every element falls into one hashed bin, in the
    next `size` rounds all fall into the bin of that number, so each bin is filled. A bin keeps the least (round, hash), and a
    set whose bins are all full takes no part in later rounds."""
    full = np.uint64(0xFFFFFFFFFFFFFFFF)
    s = np.full(n * size, full)
    shift = U64(64 - size.bit_length() + 1)
    base, live = doc * size, np.arange(n)
    for r in range(2 * size):
        if not len(h):
            break
        x = mix(h + U64((r + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
        at = base + (x >> shift).astype(np.int64) if r < size else base + (r - size)
        if r:  # a bin filled in an earlier round keeps what it has
            hit = np.flatnonzero(s[at] == full)
            at, x = at[hit], x[hit]
        np.minimum.at(s, at, U64(r << 32) | (x & U64(0xFFFFFFFF)))
        if r < 3 or r % 2 or r >= size:
            live = live[(s.reshape(n, size)[live] == full).any(1)]
            open_ = np.zeros(n, bool)
            open_[live] = True
            keep = open_[doc]
            if not keep.all():
                h, doc, base = h[keep], doc[keep], base[keep]
    return (mix(s) >> U64(32)).astype(np.uint32).view(np.int32).reshape(n, size)
