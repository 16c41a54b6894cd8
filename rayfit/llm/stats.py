"""Document statistics, vectorised, as inputs of the quality and domain models."""

from __future__ import annotations

import numpy as np

from .textkit import Words

NAMES = ["log_bytes", "log_words", "word_len", "word_len_sd", "upper", "digit", "punct", "symbol", "bang", "pipe", "non_ascii", "lines", "line_len", "upper_words", "symbol_words", "distinct", "top_word", "repeat_lines", "ends", "short_words", "long_words", "entropy", "amp", "stops"]


def _lut(chars: str) -> np.ndarray:
    t = np.zeros(256, bool)
    t[[ord(c) for c in chars]] = True
    return t


UPPER, DIGIT = _lut("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), _lut("0123456789")
PUNCT, SYMBOL = _lut(".,;:?'\"()-"), _lut("#$%&*+/<=>@[\\]^_`{|}~")
LETTER = _lut("abcdefghijklmnopqrstuvwxyz") | UPPER
LETTER[0xC3:] = True


def of(words: Words) -> np.ndarray:
    """One row of len(NAMES) numbers for each text; all 0 for an empty one."""
    raw, edge, n = words.raw, words.edge, words.rows
    size = np.diff(edge).astype(float)
    at_least = np.maximum(size, 1)

    def share(mask):
        c = np.r_[0, np.cumsum(mask)]
        return (c[edge[1:]] - c[edge[:-1]]) / at_least

    count = np.diff(words.first).astype(float)
    per_word = np.maximum(count, 1)
    length = (words.end - words.start).astype(float)

    def by_row(x):
        return np.bincount(words.row, weights=x, minlength=n)

    def in_words(mask):
        c = np.r_[0, np.cumsum(mask)]
        return c[words.end] - c[words.start]

    mean = by_row(length) / per_word
    sd = np.sqrt(np.maximum(by_row(length**2) / per_word - mean**2, 0))
    letters = in_words(LETTER[raw])
    upper_words = by_row((in_words(UPPER[raw]) == letters) & (letters > 1)) / per_word
    symbol_words = by_row(in_words(SYMBOL[raw]) > 0) / per_word
    h = words.hashes()
    out = np.zeros((n, len(NAMES)))
    newline = raw == 10
    lines = share(newline) * at_least + (size > 0)
    distinct, top, repeat, entropy, stops = (np.zeros(n) for _ in range(5))
    breaks = np.flatnonzero(newline)
    line_first = np.searchsorted(breaks, edge)
    for r in range(n):
        a, b = words.first[r], words.first[r + 1]
        if b == a:
            continue
        _, c = np.unique(h[a:b], return_counts=True)
        distinct[r], top[r] = len(c) / np.sqrt(b - a), c.max() / (b - a)
        entropy[r] = -np.sum(c / (b - a) * np.log(c / (b - a)))
        stops[r] = np.sort(c)[-10:].sum() / (b - a)
        cuts = breaks[line_first[r] : line_first[r + 1]]
        if len(cuts):
            ends = np.searchsorted(words.start[a:b], cuts)
            sums = np.add.reduceat(np.r_[h[a:b], np.uint64(0)], np.unique(np.r_[0, np.minimum(ends, b - a - 1)]))
            repeat[r] = 1 - len(np.unique(sums)) / len(sums)
    out[:] = np.stack([np.log1p(size), np.log1p(count), mean, sd, share(UPPER[raw]), share(DIGIT[raw]), share(PUNCT[raw]), share(SYMBOL[raw]), share(raw == 33), share(raw == 124), share(raw >= 128), np.log1p(lines), np.log1p(size / np.maximum(lines, 1)), upper_words, symbol_words, distinct, top, repeat, by_row(np.isin(raw[words.end - 1], [46, 33, 63])) / per_word, by_row(length <= 3) / per_word, by_row(length >= 12) / per_word, entropy, share(raw == 38), stops], 1)
    out[size == 0] = 0
    return out
