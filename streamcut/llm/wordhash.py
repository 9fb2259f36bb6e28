"""Vectorised word and shingle hashing shared by the word-based operators.

Whole Arrow batches are hashed at once with numpy.  A word's 64-bit id is a polynomial over random byte codes
(arithmetic modulo 2**64), passed through a finalising mixer; a shingle's id is the same polynomial over word ids.
Two different shingles share an id with probability about 2**-64, which the operators treat as never.
"""

from __future__ import annotations

import numpy as np

_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15)
_STEP = _U(0xD6E8FEB86659FD93)


def _inverse(odd: int) -> int:
    return pow(odd, -1, 1 << 64)


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of the splitmix generator: every input bit reaches every output bit."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_CODES = mix(np.arange(1, 257, dtype=_U) * _BASE)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_ALNUM = np.zeros(256, dtype=bool)
_ALNUM[48:58] = _ALNUM[97:123] = _ALNUM[65:91] = _ALNUM[128:] = True


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=_U)
    if n:
        out[0] = 1
        np.multiply.accumulate(out, out=out)
    return out


_GROWN: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(16, int(n).bit_length())
    if 0 not in _GROWN or len(_GROWN[0][0]) < n:
        _GROWN[0] = (_powers(int(_STEP), size), _powers(_inverse(int(_STEP)), size))
    return _GROWN[0]


class Spans:
    """64-bit ids of stretches [first, last) of a run of codes."""

    def __init__(self, codes: np.ndarray):
        up, self.down = _tables(len(codes) + 1)
        self.total = np.zeros(len(codes) + 1, dtype=_U)
        np.cumsum(codes * up[: len(codes)], out=self.total[1:])

    def ids(self, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        return mix((self.total[last] - self.total[first]) * self.down[first] + (last - first).astype(_U) * _BASE)


def hash_spans(joined: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """64-bit ids of byte stretches."""
    return Spans(_CODES[joined]).ids(first, last)


def point_codes(points: np.ndarray) -> np.ndarray:
    """Random codes of code points."""
    return mix((points.astype(_U) + _U(1)) * _BASE)


def words_of(texts: list[bytes], kind: str = "space", lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words of many texts: (ids, start byte, end byte, words per text, joined bytes).

    ``kind`` 'space': maximal runs without 0x20 and 0x09-0x0D; 'alnum': maximal runs of digits, ASCII letters and
    bytes from 0x80 on.  Offsets are into the joined bytes, where one blank follows each text.
    """
    joined = np.frombuffer(b" ".join(texts) + b" ", dtype=np.uint8)
    inside = _ALNUM[joined] if kind == "alnum" else ~_SPACE[joined]
    edge = np.flatnonzero(np.diff(inside, prepend=False, append=False))
    first, last = edge[0::2], edge[1::2]
    low = _LOWER[joined] if lower else joined
    ids = hash_spans(low, first, last)
    ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), dtype=np.int64, count=len(texts)))
    upto = np.searchsorted(first, ends, side="left")
    return ids, first, last, np.diff(upto, prepend=0), low


def windows(ids: np.ndarray, counts: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids of all windows of ``size`` consecutive words inside one text: (ids, index of first word, windows per text).

    A text with fewer words, but not none, has one window made of all of them.
    """
    n = len(ids)
    ends = np.cumsum(counts)
    begins = ends - counts
    short = (counts > 0) & (counts < size)
    per = np.where(counts >= size, counts - size + 1, short.astype(np.int64))
    if not n:
        return ids[:0], begins[:0], per
    up, down = _tables(n + 1)
    total = np.zeros(n + 1, dtype=_U)
    np.cumsum(ids * up[:n], out=total[1:])
    place = np.arange(per.sum()) - np.repeat(np.cumsum(per) - per, per) + np.repeat(begins, per)
    length = np.repeat(np.where(short, counts, size), per)
    out = mix((total[place + length] - total[place]) * down[place] + length.astype(_U) * _BASE)
    return out, place, per
