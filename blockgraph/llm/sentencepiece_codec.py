"""Operator 9: SentencePiece (merge type) encoding with seeded merge dropout, and decoding.

A text becomes units that no piece can cross: a run of spaces with the characters up to the next space. A unit is
segmented by repeatedly merging the candidate pair of best score, leftmost first, as the library's agenda does;
with dropout, a candidate is skipped for good if a keyed hash of (seed, document id, number of the unit in its text, unit,
place, piece) falls below the rate. So every occurrence of a word draws anew, and as the key knows nothing of partitions or
batches, results repeat exactly. With rate 0 the result is the library's, and equal units are segmented once per slice.

All units of a slice are segmented at once, one merge per unit and step, in matrices by unit
length; units longer than ``LONG`` symbols use a heap each. Decoding concatenates the pieces' bytes and is lossless: characters
that the vocabulary lacks, and a literal U+2581, are spelt in byte pieces.

Defined cases: null and empty texts have no pieces and decode to an empty text; a null ``doc_id`` draws as 0 does; equal
(text, doc_id) rows have equal pieces; a text of any length is taken whole, at least one to a slice; an empty table gives an empty
one; other columns are not read, and :func:`decode_pieces` replaces a column ``decoded`` that is there already.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .text import factorize, ragged, rows_of, slices, span_hashes, splitmix, utf8

SEED, RATE = 1729, 0.1
SLICE = 1 << 20
LONG = 48
_NONE = np.int32(2**31 - 1)
_META = "▁".encode()


class Vocabulary:
    """Pieces of a model: their bytes (with a space for U+2581), merges and ranks."""

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.size = model.get_piece_size()
        self.bytes: list[bytes] = []
        ids: dict[bytes, int] = {}
        self.byte_piece = np.zeros(256, np.int32)
        order = []
        for i in range(self.size):
            piece = model.id_to_piece(i)
            if model.is_byte(i):
                self.byte_piece[int(piece[3:5], 16)] = i
                self.bytes.append(bytes([int(piece[3:5], 16)]))
            elif model.is_control(i) or model.is_unknown(i) or model.is_unused(i):
                self.bytes.append(b"")
            else:
                spelt = piece.encode().replace(_META, b" ")
                self.bytes.append(spelt)
                ids[spelt] = i
                order.append((-model.get_score(i), i))
        self.ids = ids
        rank = np.full(self.size, _NONE, np.int32)
        scores = sorted(order)
        level, last = -1, None
        for score, i in scores:
            level += score != last
            last = score
            rank[i] = level
        self.rank = rank
        # Every way to write a piece as two pieces.
        pairs: dict[int, int] = {}
        for spelt, i in ids.items():
            for cut in range(1, len(spelt)):
                left, right = ids.get(spelt[:cut]), ids.get(spelt[cut:])
                if left is not None and right is not None:
                    pairs[left * self.size + right] = i
        self.pair_keys, self.pair_ids = hash_table(pairs)
        taken = self.pair_keys != -1
        # The longest run of taken slots bounds the probing.
        edges = np.flatnonzero(np.diff(np.concatenate([[0], taken.astype(np.int8), [0]])))
        self.probes = int((edges[1::2] - edges[::2]).max(initial=0))
        self.lengths = np.array([len(b) for b in self.bytes], np.int64)
        self.flat = np.frombuffer(b"".join(self.bytes), np.uint8)
        self.starts = np.cumsum(self.lengths) - self.lengths
        # Characters: id of the piece that is this one character, by its bytes packed into a number.
        chars = {int.from_bytes(s, "big"): i for s, i in ids.items() if len(s) <= 4 and len(s.decode("utf-8", "ignore")) == 1 and s != _META}
        self.char_keys = np.array(sorted(chars), np.int64)
        self.char_ids = np.array([chars[k] for k in self.char_keys.tolist()], np.int32)

    def merged(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The piece that two symbols make, or -1. Negative symbols are characters without a piece."""
        key = left.astype(np.int64) * self.size + right
        key[(left < 0) | (right < 0)] = -2
        slot = _slots(key, len(self.pair_keys))
        found = np.where(self.pair_keys[slot] == key, self.pair_ids[slot], -1)
        for _ in range(self.probes):
            miss = np.flatnonzero((found < 0) & (self.pair_keys[slot] != -1))
            if not len(miss):
                break
            slot[miss] = (slot[miss] + 1) % len(self.pair_keys)
            hit = self.pair_keys[slot[miss]] == key[miss]
            found[miss[hit]] = self.pair_ids[slot[miss[hit]]]
        return found


def _slots(key: np.ndarray, size: int) -> np.ndarray:
    return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - size.bit_length() + 1)).astype(np.int64)


def hash_table(pairs: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """Open addressing over a power of two of slots, an eighth full at most; -1 marks free slots."""
    size = 1 << max(4, (8 * len(pairs)).bit_length())
    keys, values = np.full(size, -1, np.int64), np.zeros(size, np.int32)
    order = np.array(list(pairs), np.int64)
    for key, slot in zip(order.tolist(), _slots(order, size).tolist(), strict=True):
        while keys[slot] != -1:
            slot = (slot + 1) % size
        keys[slot], values[slot] = key, pairs[key]
    return keys, values


@cache
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


def _dropped(key: np.ndarray, place: np.ndarray, piece: np.ndarray, rate: float) -> np.ndarray:
    mixed = splitmix(key ^ (place.astype(np.uint64) << np.uint64(32)) ^ piece.astype(np.uint64))
    return (mixed >> np.uint64(11)) < np.uint64(int(rate * (1 << 53)))


def _offers(v: Vocabulary, left, right, key, place, rate: float) -> tuple[np.ndarray, np.ndarray]:
    """Piece and rank of candidate merges; skipped ones get no rank."""
    piece = v.merged(left, right)
    rank = np.where(piece >= 0, v.rank[np.maximum(piece, 0)], _NONE)
    if rate > 0:
        rank = np.where((piece >= 0) & _dropped(key, place, np.maximum(piece, 0), rate), _NONE, rank)
    return piece, rank


def merge_one(v: Vocabulary, symbols: list[int], key: int, rate: float) -> list[int]:
    """Agenda processing of one unit with a heap."""
    n = len(symbols)
    symbols, after, before = list(symbols), list(range(1, n + 1)), list(range(-1, n - 1))
    alive = [True] * n
    agenda: list[tuple[int, int, int, int, int]] = []

    def offer(i: int, j: int) -> None:
        piece, rank = _offers(v, np.array([symbols[i]]), np.array([symbols[j]]), np.array([key], np.uint64), np.array([i]), rate)
        if rank[0] != _NONE:
            heapq.heappush(agenda, (int(rank[0]), i, j, int(piece[0]), symbols[i] * v.size + symbols[j]))

    for i in range(n - 1):
        offer(i, i + 1)
    while agenda:
        _, i, j, piece, stamp = heapq.heappop(agenda)
        if not (alive[i] and alive[j]) or after[i] != j or symbols[i] * v.size + symbols[j] != stamp:
            continue
        symbols[i] = piece
        alive[j] = False
        after[i] = after[j]
        if after[i] < n:
            before[after[i]] = i
            offer(i, after[i])
        if before[i] >= 0:
            offer(before[i], i)
    return [s for s, a in zip(symbols, alive, strict=True) if a]


def merge_many(v: Vocabulary, symbols: np.ndarray, size: np.ndarray, key: np.ndarray, rate: float) -> tuple[np.ndarray, np.ndarray]:
    """Agenda processing of many short units: a row each, one merge per row and step. Returns symbols and sizes.

    Symbols stay where their first character is, linked to the ones before and after, so a step touches a few cells of a row."""
    s, (n, width) = symbols.copy(), symbols.shape
    places = np.arange(width)
    after = np.tile((places + 1).astype(np.int16), (n, 1))
    before = np.tile((places - 1).astype(np.int16), (n, 1))
    alive = places < size[:, None]
    piece, rank = np.full((n, width), -1, np.int32), np.full((n, width), _NONE, np.int32)
    a, b = np.nonzero(places < (size - 1)[:, None])
    piece[a, b], rank[a, b] = _offers(v, s[a, b], s[a, b + 1], key[a], b, rate)
    rows = np.arange(n)
    while len(rows):
        offered = rank[rows]
        at = offered.argmin(axis=1)
        busy = np.take_along_axis(offered, at[:, None], 1)[:, 0] != _NONE
        rows, at = rows[busy], at[busy]
        gone = after[rows, at]
        s[rows, at] = piece[rows, at]
        alive[rows, gone] = False
        rank[rows, gone] = _NONE
        rank[rows, at] = _NONE
        behind = after[rows, gone]
        after[rows, at] = behind
        inner = behind < size[rows]
        before[rows[inner], behind[inner]] = at[inner]
        ahead = before[rows, at]
        first = ahead >= 0
        # The new symbol with the next one, and the one before with it.
        x = np.concatenate([rows[inner], rows[first]])
        left = np.concatenate([at[inner], ahead[first]])
        right = np.concatenate([behind[inner], at[first]])
        piece[x, left], rank[x, left] = _offers(v, s[x, left], s[x, right], key[x], left, rate)
    found = alive.sum(axis=1)
    out = np.full((n, width), -1, np.int32)
    out[places < found[:, None]] = s[alive]
    return out, found


def units(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The slice with a space put before every non-empty text, its new offsets, and the unit starts."""
    filled = np.diff(offs) > 0
    shift = np.concatenate([[0], np.cumsum(filled)])
    moved = offs + shift
    spelt = np.full(moved[-1], 32, np.uint8)
    spelt[np.arange(len(data)) + np.repeat(shift[1:], np.diff(offs))] = data
    space = spelt == 32
    begin = space.copy()
    begin[1:] &= ~space[:-1]
    begin[moved[:-1][filled]] = True
    return spelt, moved, np.flatnonzero(begin)


def segment(v: Vocabulary, spelt: np.ndarray, starts: np.ndarray, ends: np.ndarray, keys: np.ndarray, rate: float) -> tuple[np.ndarray, np.ndarray]:
    """Piece ids of the given units, one after another, and their numbers."""
    at = ragged(starts, ends - starts)
    flat = spelt[at]
    owner = np.repeat(np.arange(len(starts)), ends - starts)
    head = (flat & 0xC0) != 0x80
    pos = np.flatnonzero(head)
    width = np.diff(np.append(pos, len(flat)))
    packed = flat[pos].astype(np.int64)
    for k in (1, 2, 3):
        more = width > k
        packed[more] = packed[more] << 8 | flat[pos[more] + k]
    found = np.minimum(np.searchsorted(v.char_keys, packed), len(v.char_keys) - 1)
    symbol = np.where(v.char_keys[found] == packed, v.char_ids[found], -1 - np.arange(len(packed)))
    unit = owner[pos]
    size = np.bincount(unit, minlength=len(starts))
    first = np.cumsum(size) - size
    parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    low = 0
    for high in (2, 4, 6, 8, 12, 16, 24, 32, LONG):
        some = np.flatnonzero((size > low) & (size <= high))
        low = high
        if len(some):
            grid = np.full((len(some), high), -1, np.int32)
            inside = np.arange(high) < size[some][:, None]
            grid[inside] = symbol[ragged(first[some], size[some])]
            merged, n = merge_many(v, grid, size[some], keys[some], rate)
            parts.append((some, n, merged[np.arange(high) < n[:, None]]))
    for i in np.flatnonzero(size > LONG).tolist():
        merged = merge_one(v, symbol[first[i] : first[i] + size[i]].tolist(), int(keys[i]), rate)
        parts.append((np.array([i]), np.array([len(merged)]), np.array(merged, np.int64)))
    count = np.zeros(len(starts), np.int64)
    for some, n, _ in parts:
        count[some] = n
    place = np.cumsum(count) - count
    symbols = np.zeros(count.sum(), np.int64)
    for some, n, values in parts:
        symbols[ragged(place[some], n)] = values
    # Characters without a piece become byte pieces.
    lost = symbols < 0
    if lost.any():
        code = packed[np.where(lost, -1 - symbols, 0)]
        spread = np.where(lost, 1 + (code > 0xFF) + (code > 0xFFFF) + (code > 0xFFFFFF), 1)
        index = np.repeat(np.arange(len(symbols)), spread)
        rest = np.repeat(np.cumsum(spread), spread) - np.arange(spread.sum()) - 1
        byte = code[index] >> (8 * rest) & 0xFF
        by_unit = np.bincount(np.repeat(np.arange(len(starts)), count), spread, minlength=len(starts)).astype(np.int64)
        symbols = np.where(lost[index], v.byte_piece[byte], symbols[index])
        count = by_unit
    return symbols.astype(np.int32), count


def encode_slice(v: Vocabulary, data: np.ndarray, offs: np.ndarray, ids: np.ndarray, seed: int, rate: float) -> tuple[np.ndarray, np.ndarray]:
    """Piece ids of all texts of a slice, whose documents have these 64-bit ids, and the n+1 offsets of the texts."""
    spelt, moved, starts = units(data, offs)
    ends = np.append(starts[1:], len(spelt))
    if not len(starts):
        return np.zeros(0, np.int32), np.zeros(len(offs), np.int64)
    key = span_hashes(spelt, starts, ends)
    if rate > 0:
        doc = np.searchsorted(moved, starts, "right") - 1
        number = np.arange(len(starts)) - np.searchsorted(starts, moved)[doc]
        draws = splitmix(splitmix(ids.astype(np.uint64) ^ np.uint64(seed << 32))[doc] + number.astype(np.uint64))
        pieces, count = segment(v, spelt, starts, ends, key ^ draws, rate)
    else:
        codes, distinct, first = factorize(key)
        symbols, size = segment(v, spelt, starts[first], ends[first], distinct, rate)
        count = size[codes]
        pieces = symbols[ragged((np.cumsum(size) - size)[codes], count)]
    sums = np.concatenate([[0], np.cumsum(count)])
    return pieces, sums[np.searchsorted(starts, moved)]


def decode_slice(v: Vocabulary, ids: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts and their offsets: the pieces' bytes without the space put before each text."""
    length = v.lengths[ids]
    flat = v.flat[ragged(v.starts[ids], length)]
    sums = np.concatenate([[0], np.cumsum(length)])
    ends = sums[offs]
    filled = np.diff(ends) > 0
    keep = np.ones(len(flat), bool)
    keep[ends[:-1][filled]] = False
    return flat[keep], ends - np.concatenate([[0], np.cumsum(filled)])


def document_numbers(ids: pa.Array) -> np.ndarray:
    return ids.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)


def encode_pieces(docs: DataFrame, model_path: str, rate: float = RATE, seed: int = SEED) -> DataFrame:
    """doc_id and piece_ids of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = vocabulary(model_path)
        for batch in batches:
            ids = rows_of(batch, "doc_id")
            data, offs = utf8(rows_of(batch, "text"))
            numbers = document_numbers(ids)
            for i, j in slices(offs, SLICE):
                pieces, ends = encode_slice(v, data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], numbers[i:j], seed, rate)
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(pieces))], ["doc_id", "piece_ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, piece_ids array<int>")


def decode_pieces(df: DataFrame, model_path: str, column: str = "piece_ids") -> DataFrame:
    """All columns plus ``decoded``; null ids give an empty text."""

    @F.pandas_udf("string")
    def decode(lists: pd.Series) -> pd.Series:
        v = vocabulary(model_path)
        parts = [np.zeros(0, np.int32) if x is None else np.asarray(x, np.int32) for x in lists]
        flat, offs = decode_slice(v, np.concatenate([np.zeros(0, np.int32), *parts]), np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64))
        return pd.Series([flat[a:b].tobytes().decode("utf-8", "replace") for a, b in zip(offs, offs[1:], strict=False)], dtype=object)

    return df.withColumn("decoded", decode(column))


DIGESTS = "doc_id bigint, n_bytes bigint, n_pieces bigint, pieces_sha256 string, decoded_sha256 string, lossless boolean"


def piece_digests(docs: DataFrame, model_path: str, rate: float = RATE, seed: int = SEED) -> DataFrame:
    """Per document: bytes, pieces, SHA-256 of the ids (4 bytes each, little-endian) and of the decoded text, and whether it is the text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = vocabulary(model_path)
        for batch in batches:
            ids = rows_of(batch, "doc_id")
            data, offs = utf8(rows_of(batch, "text"))
            numbers = document_numbers(ids)
            for i, j in slices(offs, SLICE):
                part, cuts = data[offs[i] : offs[j]], offs[i : j + 1] - offs[i]
                pieces, ends = encode_slice(v, part, cuts, numbers[i:j], seed, rate)
                back, spans = decode_slice(v, pieces, ends)
                raw, raw_ids, raw_back = part.tobytes(), pieces.astype("<i4").tobytes(), back.tobytes()
                rows = []
                for d in range(j - i):
                    text, decoded = raw[cuts[d] : cuts[d + 1]], raw_back[spans[d] : spans[d + 1]]
                    rows.append((len(text), int(ends[d + 1] - ends[d]), hashlib.sha256(raw_ids[4 * ends[d] : 4 * ends[d + 1]]).hexdigest(), hashlib.sha256(decoded).hexdigest(), text == decoded))
                columns = zip(*rows, strict=True)
                types = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.bool_())
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), *(pa.array(c, t) for c, t in zip(columns, types, strict=True))], ["doc_id", "n_bytes", "n_pieces", "pieces_sha256", "decoded_sha256", "lossless"])

    return docs.select("doc_id", "text").mapInArrow(run, DIGESTS)


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return piece_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("piece_bpe_32k.model"))
