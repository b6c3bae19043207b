"""Weights, lanes, bins and waves of block lists."""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .blocklists import members

LANES = ("light", "heavy", "both")


def weigh(lists: DataFrame, manifest: DataFrame, weight: str | Column = "n_edges") -> DataFrame:
    """Add the weight of a list: the sum of a manifest expression over its blocks, by default the edges."""
    value = F.expr(weight) if isinstance(weight, str) else weight
    sizes = F.broadcast(manifest.select("block_id", value.cast("double").alias("_w"), F.col("bytes").alias("_b")))
    sums = members(lists).join(sizes, "block_id", "left").groupBy("list_id").agg(F.coalesce(F.sum("_w"), F.lit(0.0)).alias("weight"), F.coalesce(F.sum("_b"), F.lit(0)).alias("bytes"))
    return lists.join(sums, "list_id")


def split(weighed: DataFrame, lane: str = "both", heavy_share: float = 0.5, cutoff: float | None = None) -> DataFrame:
    """Add ``lane``: the heaviest lists up to a share of the total weight go to the vectorised lane, the rest to the SQL lane.

    ``cutoff``: lists of a larger weight never go to the SQL lane. Order: weight falling, then list_id.
    """
    if lane not in LANES:
        raise ValueError(f"unknown lane {lane!r}")
    if lane != "both":
        return weighed.withColumn("lane", F.lit(lane))
    order = W.orderBy(F.desc("weight"), "list_id")
    before = F.sum("weight").over(order.rowsBetween(W.unboundedPreceding, 0)) - F.col("weight")
    heavy = before < heavy_share * F.sum("weight").over(W.partitionBy())
    if cutoff is not None:
        heavy = heavy | (F.col("weight") > cutoff)
    return weighed.withColumn("lane", F.when(heavy, "heavy").otherwise("light"))


def bins_lpt(weighed: DataFrame, bins: int) -> DataFrame:
    """Add ``bin``: heaviest list first, each into the lightest bin so far. The lists are planning-size rows on the driver."""
    heap = [(0.0, b) for b in range(bins)]
    placed = []
    for row in weighed.select("list_id", "weight").orderBy(F.desc("weight"), "list_id").toLocalIterator():
        load, b = heapq.heappop(heap)
        placed.append((row.list_id, b))
        heapq.heappush(heap, (load + row.weight, b))
    return weighed.join(F.broadcast(weighed.sparkSession.createDataFrame(placed, "list_id long, bin int")), "list_id")


def waves(weighed: DataFrame, budget_bytes: int) -> DataFrame:
    """Add ``wave``: lists in falling weight, cut where the bytes so far pass a multiple of the budget."""
    before = F.sum("bytes").over(W.orderBy(F.desc("weight"), "list_id").rowsBetween(W.unboundedPreceding, 0)) - F.col("bytes")
    return weighed.withColumn("wave", F.floor(before / budget_bytes).cast("int"))


def choose_p(n_edges: int, block_bytes: int = 128 << 20, edge_bytes: int = 16, most: int = 4096) -> int:
    """Stripes per side so that an even block has at most ``block_bytes``."""
    p = 1
    while p < most and n_edges * edge_bytes > block_bytes * p * p:
        p += 1
    return p


def classify_density(manifest: DataFrame, dense: float = 0.1, sparse: float = 0.001) -> DataFrame:
    """Add the density of a block and its class: dense, light or sparse."""
    area = (F.col("src_hi") - F.col("src_lo")) * (F.col("dst_hi") - F.col("dst_lo"))
    density = F.when(area > 0, F.col("n_edges") / area).otherwise(0.0)
    return manifest.withColumn("density", density).withColumn("kind", F.when(F.col("density") >= dense, "dense").when(F.col("density") >= sparse, "light").otherwise("sparse"))


def autotune(manifest: DataFrame, n_vertices: int) -> dict:
    """Layout and lane from the manifest: attribute rows moved per round under either layout, and skew."""
    row = manifest.agg(F.sum("n_edges").alias("e"), F.sum(F.col("n_src") + F.col("n_dst")).alias("a2"), F.max("n_edges").alias("top"), F.avg("n_edges").alias("mean")).first()
    a1 = n_vertices + (manifest.groupBy("col").agg(F.sum("n_src").alias("s")).agg(F.sum("s")).first()[0] or 0)
    skew = (row.top or 0) / (row.mean or 1)
    return {"p": choose_p(int(row.e or 0)), "layout": "1d" if a1 <= (row.a2 or 0) else "2d", "lane": "both" if skew > 4 else "light", "alpha": 14, "beta": 24}
