"""Block numbers along space-filling curves, and hashes both engines can compute."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: A prime and a multiplier whose products stay inside 64 bits.
PRIME, MULTIPLIER = 2147483647, 48271


def row_major(row: Column, col: Column, p: int) -> Column:
    return row.cast("long") * p + col


def morton(row: Column, col: Column, p: int) -> Column:
    """Bits of row and column interleaved, the row's first."""
    out = F.lit(0).cast("long")
    for k in range(max(1, (p - 1).bit_length())):
        out = out + F.shiftleft(F.shiftright(row, k).bitwiseAND(1).cast("long"), 2 * k + 1) + F.shiftleft(F.shiftright(col, k).bitwiseAND(1).cast("long"), 2 * k)
    return out


def hilbert(row: Column, col: Column, p: int) -> Column:
    """Distance along the Hilbert curve over the smallest square of a power of two that holds p x p blocks."""
    side = 1 << max(1, (p - 1).bit_length())
    x, y, out = col.cast("long"), row.cast("long"), F.lit(0).cast("long")
    half = side // 2
    while half:
        right, up = F.shiftright(x, half.bit_length() - 1).bitwiseAND(1), F.shiftright(y, half.bit_length() - 1).bitwiseAND(1)
        out = out + half * half * (3 * right).bitwiseXOR(up)
        flip = (up == 0) & (right == 1)
        fx, fy = F.when(flip, half - 1 - F.pmod(x, F.lit(half))).otherwise(F.pmod(x, F.lit(half))), F.when(flip, half - 1 - F.pmod(y, F.lit(half))).otherwise(F.pmod(y, F.lit(half)))
        x, y = F.when(up == 0, fy).otherwise(fx), F.when(up == 0, fx).otherwise(fy)
        half //= 2
    return out


ORDERS = {"row": row_major, "morton": morton, "hilbert": hilbert}


def int_hash(x: Column, seed: int, rounds: int = 2) -> Column:
    """A number in [0, PRIME) by repeated modular multiplication."""
    for r in range(rounds):
        x = F.pmod(x * MULTIPLIER + (seed + r), F.lit(PRIME))
    return x
