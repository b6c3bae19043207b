"""Vectorised text kernels: bytes of an Arrow column, token spans, 64-bit token hashes.

All work is on the UTF-8 bytes, for a whole slice of texts at once. A token never crosses a text.
Slices hold about ``SLICE_BYTES`` of text (or one longer text), which bounds the temporary arrays.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa

# Freed batches go back to the system at once, so that idle Python workers stay small.
pa.set_memory_pool(pa.system_memory_pool())

SLICE_BYTES = 3 << 20
_HASH_BLOCK = 1 << 20
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))


def splitmix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer."""
    x = x + np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE_CODES = splitmix(np.arange(1, 257, dtype=np.uint64))
_powers = np.ones(1, np.uint64)
_inverses = np.ones(1, np.uint64)


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    global _powers, _inverses
    if len(_powers) < n:
        size = max(n, _HASH_BLOCK)
        up, down = np.full(size, _BASE), np.full(size, _INVERSE)
        up[0] = down[0] = 1
        _powers, _inverses = np.cumprod(up), np.cumprod(down)
    return _powers[:n], _inverses[:n]


class Alphabet:
    """Which bytes make words; A-Z are lower-cased first."""

    def __init__(self, keep: bytes | None = None, drop: bytes = b""):
        self.lower = np.arange(256, dtype=np.uint8)
        self.lower[65:91] += 32
        inside = np.isin(np.arange(256), list(keep)) if keep is not None else ~np.isin(np.arange(256), list(drop))
        self.word = inside[self.lower]


#: Words of ASCII digits, letters and everything beyond ASCII.
ALNUM = Alphabet(keep=bytes([*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)]))
#: Words of letters only, as far as bytes can tell.
LETTERS = Alphabet(keep=bytes([*range(0x61, 0x7B), *range(0x80, 0x100)]))
#: Words between white space.
SPACED = Alphabet(drop=bytes([0x20, *range(0x09, 0x0E)]))


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the n+1 offsets of its texts; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks)
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if len(column) == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    offs = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offs[0] : offs[-1]], offs - offs[0]


def slices(offs: np.ndarray, most: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about ``most`` bytes, one text at least."""
    i, n = 0, len(offs) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + most, "right")) - 1)
        yield i, j
        i = j


class Tokens:
    """Token spans of a slice of texts. ``first[d]:first[d+1]`` are the tokens of text d."""

    def __init__(self, data: np.ndarray, offs: np.ndarray, alphabet: Alphabet):
        self.mapped = alphabet.lower[data]
        self.offs = offs
        word = alphabet.word[data]
        begin, end = word.copy(), word.copy()
        if len(word):
            begin[1:] &= ~word[:-1]
            end[:-1] &= ~word[1:]
            inner = offs[(offs > 0) & (offs < len(word))]
            begin[inner] = word[inner]
            end[inner - 1] = word[inner - 1]
        self.starts = np.flatnonzero(begin)
        self.ends = np.flatnonzero(end) + 1
        self.first = np.searchsorted(self.starts, offs)

    def __len__(self) -> int:
        return len(self.starts)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def docs(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.offs) - 1), self.counts)

    def hashes(self) -> np.ndarray:
        return span_hashes(self.mapped, self.starts, self.ends)

    def words(self, which: np.ndarray) -> pa.Array:
        """The tokens at these positions as a binary Arrow array, in the mapped bytes."""
        return gather_spans(self.mapped, self.starts[which], self.ends[which])


def span_hashes(mapped: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit polynomial hash of each span, mixed. Begins and ends of the spans are in order."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        lo = int(starts[i])
        j = max(i + 1, int(np.searchsorted(ends, lo + _HASH_BLOCK, "right")))
        hi = int(ends[j - 1])
        up, down = _power_tables(hi - lo + 1)
        sums = np.zeros(hi - lo + 1, np.uint64)
        np.cumsum(_BYTE_CODES[mapped[lo:hi]] * up[:-1], out=sums[1:])
        s, e = starts[i:j] - lo, ends[i:j] - lo
        out[i:j] = (sums[e] - sums[s]) * down[s]
        i = j
    return splitmix(out)


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices start, start+1, ... of every span, one after another."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    before = np.cumsum(lengths) - lengths
    return np.arange(total) + np.repeat(starts - before, lengths)


def gather_spans(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> pa.Array:
    lengths = ends - starts
    offs = np.zeros(len(starts) + 1, np.int64)
    np.cumsum(lengths, out=offs[1:])
    flat = data[ragged(starts, lengths)]
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(offs), pa.py_buffer(np.ascontiguousarray(flat))])


def factorize(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Codes, distinct keys and the first position of each."""
    codes, distinct = pd.factorize(keys)
    first = np.empty(len(distinct), np.int64)
    first[codes[::-1]] = np.arange(len(keys) - 1, -1, -1)
    return codes, distinct, first


def segment_sums(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sums of values[first[d]:first[d+1]] for every d; 0 for empty ranges."""
    sums = np.zeros((len(values) + 1, *values.shape[1:]), values.dtype if values.dtype.kind in "iu" else np.float64)
    np.cumsum(values, axis=0, out=sums[1:])
    return sums[first[1:]] - sums[first[:-1]]


def fitting(rows: Iterator, most: int) -> tuple[list[str], list]:
    """Texts and labels of (text, label) rows that fit into ``most`` bytes together; one that does not fit is passed over. A label none of whose texts fits has its shortest one."""
    texts, labels, size, spare = [], [], 0, {}
    for text, label in rows:
        n = len(text.encode())
        if size + n <= most:
            size += n
            texts.append(text)
            labels.append(label)
        elif label not in spare or n < spare[label][0]:
            spare[label] = n, text
    for label in sorted(spare.keys() - set(labels)):
        texts.append(spare[label][1])
        labels.append(label)
    return texts, labels


def rows_of(table: pa.Table | pa.RecordBatch, name: str) -> pa.Array:
    column = table.column(name)
    return column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
