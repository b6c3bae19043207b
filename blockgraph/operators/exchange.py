"""Moving attributes along rows and columns of blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.program import merge


def gather(edges: DataFrame, state: DataFrame, column: str, side: str = "src") -> DataFrame:
    """Edges with the attribute of one end. Blocks lie in buckets of the source, so only the attribute rows move."""
    return edges.join(state.select(F.col("id").alias(side), F.col(column)), side)


def scatter(updates: DataFrame, column: str, combiner: str = "sum") -> DataFrame:
    """(id, value) of updates: combined where the blocks lie, then along the columns of blocks, in one exchange."""
    return merge(updates, ["id"], column, combiner)
