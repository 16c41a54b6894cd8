"""Vectorised word work on Arrow string arrays: bytes in, NumPy arrays out, no Python loop over words."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_BYTE = np.random.default_rng(11).integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BACK = np.uint64(pow(int(_BASE), -1, 2**64))
_POWERS = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words whose every output bit depends on every input bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) < n:
        for k, base in enumerate((_BASE, _BACK)):
            ones = np.full(n, base, np.uint64)
            ones[0] = 1
            _POWERS[k] = np.cumprod(ones, dtype=np.uint64)
    return _POWERS[0][:n], _POWERS[1][:n]


class Words:
    """Words of rows low..high of text: maximal runs of bytes other than 0x20 and 0x09-0x0D, A-Z lower-cased.

    data: the lower-cased bytes; raw: as they are; start, end: of each word in data; row: its row, from 0;
    first: index of each row's first word, with one more entry at the end; edge: byte offsets of the rows."""

    def __init__(self, text: pa.Array, low: int, high: int):
        text = text.slice(low, high - low)
        n = len(text)
        kind = np.int64 if pa.types.is_large_string(text.type) else np.int32
        ends = np.frombuffer(text.buffers()[1], kind, n + 1, text.offset * np.dtype(kind).itemsize).astype(np.int64)
        held = text.buffers()[2]
        self.raw = np.frombuffer(held, np.uint8)[ends[0] : ends[-1]] if held is not None and ends[-1] > ends[0] else np.zeros(0, np.uint8)
        self.edge = ends - ends[0]
        self.data = LOWER[self.raw]
        size = len(self.raw)
        ink = np.zeros(size + 1, bool)
        ink[:size] = ~SPACE[self.raw]
        opens = ink[:size].copy()
        opens[1:] &= ~ink[: size - 1] if size else True
        inner = self.edge[:-1][self.edge[:-1] < size]
        opens[inner] = ink[inner]
        closes = ink[:size] & ~ink[1:]
        inner = self.edge[1:][self.edge[1:] > 0] - 1
        closes[inner] = ink[inner]
        self.start = np.flatnonzero(opens)
        self.end = np.flatnonzero(closes) + 1
        self.first = np.searchsorted(self.start, self.edge)
        self.row = np.repeat(np.arange(n), np.diff(self.first))
        self.rows = n

    def hashes(self) -> np.ndarray:
        """64 bits for each word, from its lower-cased bytes."""
        if not len(self.start):
            return np.zeros(0, np.uint64)
        up, down = _powers(len(self.data))
        sums = np.zeros(len(self.data) + 1, np.uint64)
        np.cumsum(_BYTE[self.data] * up, dtype=np.uint64, out=sums[1:])
        return mix((sums[self.end] - sums[self.start]) * down[self.start] + (self.end - self.start).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))

    def shingles(self, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
        """The sorted distinct hashes of width-word shingles of each row, end to end, and the offsets of the rows.
        A row of fewer words has its whole sequence as the one shingle; a row without words has none."""
        h = self.hashes()
        n = np.diff(self.first)
        out, sizes = [], np.zeros(self.rows + 1, np.int64)
        total = len(h)
        code = np.zeros(total, np.uint64)
        for j in range(width):
            salt = mix(np.array([0x51ED270B + j], np.uint64))[0] | np.uint64(1)
            code[: max(0, total - j)] += h[j:] * salt
        code = mix(code)
        for r in range(self.rows):
            a, k = self.first[r], n[r]
            if k >= width:
                got = np.unique(code[a : a + k - width + 1])
            elif k:
                value = np.uint64(k)
                for x in h[a : a + k]:
                    value = mix(np.array([value + x], np.uint64))[0] * np.uint64(0xA24BAED4963EE407) + np.uint64(k)
                got = np.array([value], np.uint64)
            else:
                got = np.zeros(0, np.uint64)
            sizes[r + 1] = len(got)
            out.append(got)
        return (np.concatenate(out) if out else np.zeros(0, np.uint64)), np.cumsum(sizes)


np.seterr(over="ignore")
