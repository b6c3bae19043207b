"""The two kernels of a combining step: what edges send, summed up in SQL or in Arrow batches.

Both get (key, value) rows from the same sending function, so they differ only in who combines first: Spark's own partial
aggregation (light) or a vectorised one over whole batches (heavy). The merge of updates does the rest for either.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .program import BlockProgram, Context, single

#: Combiners that both lanes know.
VECTORISED = ("sum", "min", "max")


def in_batches(send: Callable[[Context, DataFrame], DataFrame], how: str) -> Callable[[Context, DataFrame], DataFrame]:
    """A heavy kernel: the rows of ``send``, combined by key within each batch."""
    if how not in VECTORISED:
        raise ValueError(f"no vectorised combiner {how!r}")

    def kernel(ctx: Context, edges: DataFrame) -> DataFrame:
        rows = send(ctx, edges)
        key, value = rows.columns

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                found = pa.Table.from_batches([batch]).group_by(key).aggregate([(value, how)])
                yield from found.select([key, f"{value}_{how}"]).rename_columns([key, value]).to_batches()

        return rows.mapInArrow(run, rows.schema)

    return kernel


def combining(send: Callable[[Context, DataFrame], DataFrame], how: str, after: Callable, **options) -> BlockProgram:
    """A program over single blocks whose updates stay a plan until ``after`` merges and uses them."""
    return BlockProgram(light=send, heavy=in_batches(send, how), lists=single, after=after, lazy=True, **options)
