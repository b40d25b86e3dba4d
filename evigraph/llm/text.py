"""Array kernels over the raw UTF-8 bytes of a column: words, word hashes, shingles."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

_U = np.uint64
_R = _U(0x9E3779B97F4A7C15 | 1)
_R_INV = _U(pow(int(_R), -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """Finalizer that spreads every input bit over all 64 output bits."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_BYTE = mix(np.arange(1, 257, dtype=_U) * _U(0x9E3779B97F4A7C15))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Bytes of words between white space, and of words of letters and digits (all non-ASCII included).
SPACED = np.ones(256, bool)
SPACED[[0x20, *range(0x09, 0x0E)]] = False
ALNUM = np.zeros(256, bool)
ALNUM[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100)]] = True

_POW: list[np.ndarray] = [np.ones(1, _U), np.ones(1, _U)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POW[0]) < n:
        size = max(n, 1 << 20)
        for k, r in ((0, _R), (1, _R_INV)):
            p = np.full(size, r, _U)
            p[0] = 1
            _POW[k] = np.multiply.accumulate(p)
    return _POW[0][:n], _POW[1][:n]


class Rolling:
    """Hash of any run of ``data`` (bytes or code points) in constant time."""

    def __init__(self, data: np.ndarray):
        p, self.inverse = powers(len(data) + 1)
        self.sums = np.zeros(len(data) + 1, _U)
        values = _BYTE[data] if data.dtype == np.uint8 else mix(data.astype(_U) * _U(0x9E3779B97F4A7C15) + _U(1))
        np.cumsum(values * p[: len(data)], out=self.sums[1:])

    def of(self, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[begin]) * self.inverse[begin] + (end - begin).astype(_U) * _U(0xD6E8FEB86659FD93))


def hash_of(text: str | bytes) -> int:
    """The hash that ``Rolling`` gives the same bytes."""
    b = np.frombuffer(text.encode() if isinstance(text, str) else text, np.uint8)
    return int(Rolling(b).of(np.array([0]), np.array([len(b)]))[0])


def points(body: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The code points of UTF-8 rows, and each row's offsets in them."""
    data = np.frombuffer(body.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), np.uint32)
    return data, np.concatenate([[0], np.cumsum((body & 0xC0) != 0x80)])[at]


@dataclass
class Words:
    """Words of the rows of a slice: byte runs, hashes, and where each row's words begin and end."""

    data: np.ndarray
    begin: np.ndarray
    end: np.ndarray
    hashes: np.ndarray
    bounds: np.ndarray

    @property
    def rows(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.bounds) - 1), np.diff(self.bounds))


def words(body: np.ndarray, at: np.ndarray, kind: np.ndarray = SPACED) -> Words:
    """Lower-case A-Z and find the maximal runs of ``kind`` bytes; runs end where rows end."""
    data = LOWER[body]
    inside = np.zeros(len(data) + 2, bool)
    inside[1:-1] = kind[body]
    begins = inside[1:-1] & ~inside[:-2]
    ends = inside[1:-1] & ~inside[2:]
    cut = at[1:-1]
    cut = cut[(cut > 0) & (cut < len(data))]
    cut = cut[inside[cut] & inside[cut + 1]]  # a run goes on over the border of two rows
    begins[cut] = True
    ends[cut - 1] = True
    begin, end = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    return Words(data, begin, end, Rolling(data).of(begin, end), np.searchsorted(begin, at))


def shingles(w: Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the word n-grams of each row, in text order, and each row's bounds in them. A row of
    fewer words, but not none, has its whole sequence as the only one."""
    n = np.diff(w.bounds)
    count = np.where(n >= size, n - size + 1, np.minimum(n, 1))
    bounds = np.zeros(len(count) + 1, np.int64)
    np.cumsum(count, out=bounds[1:])
    first = np.repeat(w.bounds[:-1] - bounds[:-1], count) + np.arange(bounds[-1])
    length = np.repeat(np.minimum(n, size), count)
    out = np.zeros(len(first), _U)
    for k in range(size):
        has = length > k
        x = np.zeros(len(first), _U)
        x[has] = w.hashes[first[has] + k]
        out = np.where(has, mix(out * _U(0x100000001B3) + x + _U(k + 1)), out)
    return out, bounds


def rare_first(tokens: np.ndarray, w: Words, size: int) -> np.ndarray:
    """Shingle hashes whose unsigned order puts long shingles, which tend to be rare, first."""
    n = np.diff(w.bounds)
    count = np.where(n >= size, n - size + 1, np.minimum(n, 1))
    first = np.repeat(w.bounds[:-1] - np.cumsum(count) + count, count) + np.arange(count.sum())
    sums = np.concatenate([[0], np.cumsum(w.end - w.begin)])
    length = sums[np.minimum(first + size, np.repeat(w.bounds[1:], count))] - sums[first]
    return (np.uint64(63) - np.minimum(length, 63).astype(_U)) << _U(58) | tokens >> _U(6)
