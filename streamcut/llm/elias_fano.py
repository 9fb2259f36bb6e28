"""Elias-Fano coded levels of an n-gram trie, and the two-level trie that language-model scoring queries."""

from __future__ import annotations

import mmap
import tempfile

import numpy as np

_U = np.uint64
#: Elements that a search decodes at once.
BLOCK = 1 << 15
#: Steps of the quantised log10 values in one decade.
STEPS = 2048


def mapped(a: np.ndarray) -> np.ndarray:
    """The array in an unlinked temporary file, mapped read-only: pages leave memory when others need it."""
    if not a.nbytes:
        return a
    with tempfile.TemporaryFile() as f:
        f.write(memoryview(a).cast("B"))
        f.flush()
        return np.frombuffer(mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ), dtype=a.dtype).reshape(a.shape)


class EliasFano:
    """A monotone sequence of unsigned numbers: low bits packed, high bits in unary."""

    def __init__(self, values: np.ndarray):
        self.n = len(values)
        top = int(values[-1]) + 1 if self.n else 1
        self.l = min(56, max(0, (top // max(1, self.n)).bit_length() - 1))
        l = _U(self.l)
        low = values & _U((1 << self.l) - 1)
        rows = np.zeros((-(-self.n // 8), self.l + 16), dtype=np.uint8)
        for k in range(8):
            bit = k * self.l
            part = (low[k::8] << _U(bit & 7)).astype("<u8").view(np.uint8).reshape(-1, 8)
            rows[: len(part), bit >> 3 : (bit >> 3) + 8] |= part
        self.low = mapped(np.concatenate([rows[:, : self.l].ravel(), np.zeros(16, np.uint8)]))
        high = (values >> l).astype(np.int64)
        place = high + np.arange(self.n)
        bits = np.zeros((int(place[-1]) + 8) // 8 if self.n else 0, dtype=np.uint8)
        bits = np.packbits(np.bincount(place, minlength=8 * len(bits)).astype(np.uint8), bitorder="little") if self.n else bits
        self.high = mapped(bits)
        #: First value and bit position of each block.
        self.first = values[::BLOCK].copy()
        self.at = place[::BLOCK].copy()

    def nbytes(self) -> int:
        return self.low.nbytes + self.high.nbytes

    def decode(self, block: int) -> np.ndarray:
        begin, end = block * BLOCK, min(self.n, (block + 1) * BLOCK)
        bit = int(self.at[block])
        stop = (int(self.at[block + 1]) if block + 1 < len(self.at) else 8 * len(self.high) - 1) // 8 + 1
        ones = np.flatnonzero(np.unpackbits(self.high[bit // 8 : stop], bitorder="little"))
        ones = ones[ones >= bit % 8][: end - begin] + bit // 8 * 8
        high = (ones - np.arange(begin, end)).astype(_U)
        if not self.l:
            return high
        i = np.arange(begin, end, dtype=np.int64) * self.l
        words = np.ndarray((len(self.low) - 8,), dtype="<u8", buffer=self.low.data, strides=(1,))
        return high << _U(self.l) | (words[i >> 3] >> (i & 7).astype(_U)) & _U((1 << self.l) - 1)

    def all(self) -> np.ndarray:
        return np.concatenate([self.decode(b) for b in range(len(self.first))]) if self.n else np.zeros(0, _U)

    def successor(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index, value) of the first element that isn't below each of the sorted queries; index n if there is none."""
        index = np.full(len(queries), self.n, dtype=np.int64)
        value = np.zeros(len(queries), dtype=_U)
        # The block that may hold a query's successor is the last one that begins below it.
        block = np.maximum(np.searchsorted(self.first, queries, side="left") - 1, 0)
        cuts = np.concatenate(([0], np.flatnonzero(np.diff(block)) + 1, [len(queries)])) if len(queries) and self.n else [0]
        for a, b in zip(cuts[:-1], cuts[1:]):
            k = int(block[a])
            values = self.decode(k)
            at = np.searchsorted(values, queries[a:b])
            inside = at < len(values)
            index[a:b] = k * BLOCK + at
            value[a:b][inside] = values[at[inside]]
            if not inside.all() and k + 1 < len(self.first):
                value[a:b][~inside] = self.first[k + 1]
        return index, value


def quantise(log10: np.ndarray) -> np.ndarray:
    return np.clip(np.rint(log10 * STEPS), -32768, 32767).astype(np.int16)


class Trie:
    """Two levels: words, and the contexts seen before each word.

    Level 1 is the sorted word ids with a quantised log10 probability each and monotone pointers to their children;
    level 2 holds the children's context codes, relative to their word's rank, with a quantised value each.
    """

    CONTEXT_BITS = 40

    def __init__(self, words: np.ndarray, word_log: np.ndarray, begins: np.ndarray, contexts: np.ndarray, context_log: np.ndarray):
        rank = np.repeat(np.arange(len(words), dtype=_U), np.diff(begins))
        self.words = EliasFano(words)
        self.pointers = EliasFano(begins.astype(_U))
        self.contexts = EliasFano(rank << _U(self.CONTEXT_BITS) | contexts)
        self.word_log, self.context_log = mapped(quantise(word_log)), mapped(quantise(context_log))

    def word(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rank or -1, log10 probability) of sorted word ids."""
        index, value = self.words.successor(queries)
        known = (index < self.words.n) & (value == queries)
        rank = np.where(known, index, -1)
        return rank, np.where(known, self.word_log[np.maximum(rank, 0)] if len(self.word_log) else 0, 0) / STEPS

    def after(self, rank: np.ndarray, contexts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(seen, log10 value) of contexts of words given by rank, sorted by both; a rank of -1 has no contexts."""
        seen, log = np.zeros(len(rank), dtype=bool), np.zeros(len(rank))
        known = np.flatnonzero(rank >= 0)
        query = rank[known].astype(_U) << _U(self.CONTEXT_BITS) | contexts[known]
        index, value = self.contexts.successor(query)
        hit = (index < self.contexts.n) & (value == query)
        seen[known] = hit
        log[known[hit]] = self.context_log[index[hit]] / STEPS
        return seen, log
