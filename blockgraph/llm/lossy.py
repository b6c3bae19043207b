"""Lossy sets of a bounded size: they may hold more than was put in, never less."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most bits of a set (16 MB), and the most values up to which it is worth a pass: a quarter full at most.
MOST_BITS, MOST_FILTERED = 27, 1 << 25


def bitmap(values: DataFrame, n: int) -> np.ndarray:
    """A bitmap of the n mixed 64-bit values of the one column, by their uppermost bits; at most 2^``MOST_BITS`` bits."""
    bits = min(MOST_BITS, max(16, math.ceil(math.log2(16 * n + 1))))
    slot = values.select(F.shiftrightunsigned(values.columns[0], 64 - bits).alias("s"))
    maps = slot.groupBy(F.bitmap_bucket_number("s").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("s")).alias("bits"))
    out = np.zeros(1 << bits >> 3, np.uint8)
    for row in maps.toLocalIterator():  # at most 2^MOST_BITS / 32768 rows of 4 KB
        at = max(row.bucket - 1, 0) * 4096
        part = np.frombuffer(bytes(row.bits), np.uint8)[: len(out) - at]
        out[at : at + len(part)] |= part
    return out


def held(bits: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Which values may be in the bitmap; numbering as in Spark's bitmap functions, where 1 is the first bit."""
    slot = (values.view(np.uint64) >> np.uint64(64 - (len(bits).bit_length() + 2))).astype(np.int64)
    bit = np.maximum(slot - 1, 0)
    return (bits[bit >> 3] >> (bit & 7).astype(np.uint8) & 1).astype(bool)


def id_bitmap(ids: DataFrame) -> np.ndarray:
    """A bitmap of the hashes of the one column."""
    ids = ids.select(F.xxhash64(ids.columns[0]).alias("h"))
    return bitmap(ids, ids.count())
