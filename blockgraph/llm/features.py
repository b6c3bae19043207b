"""Hashed subword features of distinct words: affixes, inner n-grams and the word itself, as bucket numbers."""

from __future__ import annotations

import numpy as np

from .text import LETTERS, Tokens, ragged, splitmix

#: Longer words, such as sentences without spaces, are taken in pieces.
LONGEST_WORD = 32
_STEP = np.uint64(0xC2B2AE3D27D4EB4F)
_SEED = splitmix(np.arange(1, 257, dtype=np.uint64))


def letter_words(data: np.ndarray, offs: np.ndarray) -> Tokens:
    """The words of letters. Runs over ``LONGEST_WORD`` bytes become pieces of about that size that overlap by half, cut between characters."""
    tokens = Tokens(data, offs, LETTERS)
    size = tokens.ends - tokens.starts
    if (size <= LONGEST_WORD).all():
        return tokens
    step = LONGEST_WORD // 2
    n = np.maximum(1, -(-(size - LONGEST_WORD) // step) + 1)
    starts, ends = np.repeat(tokens.starts, n), np.repeat(tokens.ends, n)
    k = np.arange(len(starts)) - np.repeat(np.cumsum(n) - n, n)
    low, high = starts + k * step, np.minimum(starts + k * step + LONGEST_WORD, ends)
    for _ in range(3):  # bytes 0x80 to 0xBF go on with a character
        low -= (low > starts) & (tokens.mapped[low] >> 6 == 2)
        high -= (high < ends) & (tokens.mapped[np.minimum(high, len(data) - 1)] >> 6 == 2)
    tokens.starts, tokens.ends = low, high
    tokens.first = np.searchsorted(low, offs)
    return tokens


def word_bytes(mapped: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``<word>`` for each span as one byte string with n+1 offsets."""
    lengths = ends - starts
    offs = np.zeros(len(starts) + 1, np.int64)
    np.cumsum(lengths + 2, out=offs[1:])
    out = np.empty(offs[-1], np.uint8)
    out[offs[:-1]] = 0x3C
    out[offs[1:] - 1] = 0x3E
    out[ragged(offs[:-1] + 1, lengths)] = mapped[ragged(starts, lengths)]
    return out, offs


def subwords(data: np.ndarray, offs: np.ndarray, sizes: tuple[int, ...], buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """(word number, bucket) of every n-gram of the given sizes inside ``<word>``."""
    owner = np.repeat(np.arange(len(offs) - 1), np.diff(offs))
    words, found = [], []
    for n in sizes:
        if len(data) < n:
            continue
        h = np.full(len(data) - n + 1, np.uint64(n))
        for j in range(n):
            h = h * _STEP + _SEED[data[j : j + len(h)]]
        inside = owner[: len(h)] == owner[n - 1 :]
        words.append(owner[: len(h)][inside])
        found.append((splitmix(h[inside]) % np.uint64(buckets)).astype(np.int64))
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(words), np.concatenate(found)


def affixes(data: np.ndarray, offs: np.ndarray, sizes: tuple[int, ...], buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """(word number, bucket) of the first and last bytes of every ``<word>``, marked as such."""
    lengths = np.diff(offs)
    words, found = [], []
    for n in sizes:
        fit = np.flatnonzero(lengths >= n)
        for side, begin in ((1, offs[:-1][fit]), (2, offs[1:][fit] - n)):
            h = np.full(len(fit), np.uint64(n * 4 + side))
            for j in range(n):
                h = h * _STEP + _SEED[data[begin + j]]
            words.append(fit)
            found.append((splitmix(h ^ np.uint64(side << 40)) % np.uint64(buckets)).astype(np.int64))
    return np.concatenate(words), np.concatenate(found)


def whole(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """A bucket for each whole word."""
    return (splitmix(hashes ^ np.uint64(0x5851F42D4C957F2D)) % np.uint64(buckets)).astype(np.int64)
