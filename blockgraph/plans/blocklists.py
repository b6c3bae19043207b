"""Ordered lists of blocks: the tasks of a block program.

A list table has (list_id, blocks ARRAY<BIGINT>). The manifest holds at most p^2 rows, so lists are joined on it alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

MAX_LISTS = 5_000_000


def _number(lists: DataFrame) -> DataFrame:
    """list_id in the order of the block numbers. There are as many rows as lists, a table of planning size."""
    return lists.select((F.row_number().over(W.orderBy("blocks")) - 1).cast("long").alias("list_id"), "blocks")


def lists_single(manifest: DataFrame) -> DataFrame:
    """Every block alone."""
    return _number(manifest.select(F.array("block_id").alias("blocks")))


def compose_custom(manifest: DataFrame, fn) -> DataFrame:
    """``fn(manifest)`` returns a column ``blocks``."""
    return _number(fn(manifest).select("blocks"))


def compose_where(manifest: DataFrame, size: int, predicate: Column | str, max_lists: int = MAX_LISTS) -> DataFrame:
    """All ordered lists of ``size`` blocks that a predicate over m1, m2, ... accepts.

    The predicate is the join condition: equalities in it make hash joins instead of products.
    """
    if size < 1:
        raise ValueError("size must be 1 or more")
    condition = F.expr(predicate) if isinstance(predicate, str) else predicate
    joined = manifest.alias("m1")
    for k in range(2, size):
        joined = joined.join(manifest.alias(f"m{k}"))
    joined = joined.join(manifest.alias(f"m{size}"), condition) if size > 1 else joined.where(condition)
    lists = joined.select(F.array(*(F.col(f"m{k}.block_id") for k in range(1, size + 1))).alias("blocks"))
    if lists.limit(max_lists + 1).count() > max_lists:
        raise ValueError(f"more than {max_lists} lists")
    return _number(lists)


def lists_triangle(manifest: DataFrame) -> DataFrame:
    """Three blocks over stripes i <= j <= h: (i, j), (i, h), (j, h). Blocks of an edge, its source's and its destination's neighbours."""
    up = manifest.where("row <= col").select("block_id", "row", "col")
    a, b, c = up.alias("a"), up.alias("b"), up.alias("c")
    lists = a.join(b, F.col("a.row") == F.col("b.row")).join(c, (F.col("c.row") == F.col("a.col")) & (F.col("c.col") == F.col("b.col")))
    return _number(lists.select(F.array("a.block_id", "b.block_id", "c.block_id").alias("blocks")))


def lists_chained(manifest: DataFrame) -> DataFrame:
    """Three blocks chained end to end from the first: second.src = first.dst, third.src = second.dst. It misses triangles; kept for comparison."""
    up = manifest.where("row <= col").select("block_id", "row", "col")
    a, b, c = up.alias("a"), up.alias("b"), up.alias("c")
    lists = a.join(b, F.col("b.row") == F.col("a.col")).join(c, (F.col("c.row") == F.col("b.col")) & (F.col("c.row") <= F.col("c.col")))
    return _number(lists.select(F.array("a.block_id", "b.block_id", "c.block_id").alias("blocks")))


PATTERNS = {"triangle": lists_triangle}


def lists_pattern(manifest: DataFrame, pattern: str = "triangle") -> DataFrame:
    if pattern not in PATTERNS:
        raise ValueError(f"unknown pattern {pattern!r}")
    return PATTERNS[pattern](manifest)


def lists_active(manifest: DataFrame, stripes, side: str = "row") -> DataFrame:
    """Single lists of the blocks whose row (or column) stripe is in ``stripes``, at most p numbers."""
    return lists_single(manifest.where(F.col(side).isin([int(s) for s in stripes])))


def members(lists: DataFrame) -> DataFrame:
    """(list_id, position, block_id)."""
    return lists.select("list_id", F.posexplode("blocks").alias("position", "block_id"))


def interval(list_id: Column, n_lists: int, size: int) -> tuple[Column, Column]:
    """The even share [lo, hi) of a global array of ``size`` entries that a list handles."""
    return F.floor(list_id * size / n_lists).cast("long"), F.floor((list_id + 1) * size / n_lists).cast("long")
