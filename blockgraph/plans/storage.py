"""Forms of a block: edge rows (COO), sorted adjacency slices (CSR), and offsets from the block's origin (compact)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SLICE = 4096


def to_csr(blocks: DataFrame, slice_size: int = SLICE) -> DataFrame:
    """(row, col, block_id, src, slice, nbrs): neighbours in rising order; hubs are cut into slices by a hash of the neighbour's rank."""
    numbered = blocks.withColumn("slice", F.floor(F.col("dst") / slice_size).cast("int"))
    return numbered.groupBy("row", "col", "block_id", "src", "slice").agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))


def to_coo(csr: DataFrame) -> DataFrame:
    return csr.select("row", "col", "block_id", "src", F.explode("nbrs").alias("dst"))


def to_compact(blocks: DataFrame, manifest: DataFrame, slice_size: int = SLICE) -> DataFrame:
    """(block_id, slice, base_src, base_dst, src_off, dst_off): 32-bit offsets, one row per slice of a block's sources."""
    based = blocks.join(F.broadcast(manifest.select("block_id", "src_lo", "dst_lo")), "block_id")
    local = based.select(
        "block_id", F.floor((F.col("src") - F.col("src_lo")) / slice_size).cast("int").alias("slice"), F.col("src_lo").alias("base_src"), F.col("dst_lo").alias("base_dst"),
        F.struct((F.col("src") - F.col("src_lo")).cast("int").alias("s"), (F.col("dst") - F.col("dst_lo")).cast("int").alias("d")).alias("e"),
    )
    packed = local.groupBy("block_id", "slice", "base_src", "base_dst").agg(F.array_sort(F.collect_list("e")).alias("e"))
    return packed.select("block_id", "slice", "base_src", "base_dst", F.col("e.s").alias("src_off"), F.col("e.d").alias("dst_off"))


def from_compact(compact: DataFrame) -> DataFrame:
    """(block_id, src, dst)."""
    pairs = compact.select("block_id", "base_src", "base_dst", F.explode(F.arrays_zip("src_off", "dst_off")).alias("e"))
    return pairs.select("block_id", (F.col("base_src") + F.col("e.src_off")).alias("src"), (F.col("base_dst") + F.col("e.dst_off")).alias("dst"))


def localise(blocks: DataFrame, manifest: DataFrame) -> DataFrame:
    """Edges by numbers from 0 inside their block's stripes."""
    based = blocks.join(F.broadcast(manifest.select("block_id", "src_lo", "dst_lo")), "block_id")
    return based.select("row", "col", "block_id", (F.col("src") - F.col("src_lo")).cast("int").alias("src"), (F.col("dst") - F.col("dst_lo")).cast("int").alias("dst"))
