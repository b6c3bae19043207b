"""A graph cut into disjoint rectangular blocks of directed edges, and its manifest."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import ORDERS
from ..operators.prepare import endpoints, symmetric
from . import cuts as cutting
from .cuts import Cuts
from .store import bucketed, fresh_path, stored

EDGE_BYTES = 16


@dataclass
class BlockedGraph:
    """Blocks (row, col, block_id, src, dst[, w]), the manifest, the vertices with their stripe, and the cuts."""

    blocks: DataFrame
    manifest: DataFrame
    vertices: DataFrame
    cuts: Cuts
    layout: str = "2d"
    #: Whether the blocks lie in buckets of the source, in the order of (src, dst).
    kept: bool = False
    #: Where each block has a folder of its own (see :func:`block_folders`), and the tables of the blocks read so far.
    path: str | None = None
    read: dict[int, DataFrame] = field(default_factory=dict)

    @property
    def p(self) -> int:
        return self.cuts.p

    def block(self, block_id: int) -> DataFrame:
        """The edges of one block, of a graph stored in folders."""
        if block_id not in self.read:
            self.read[block_id] = self.manifest.sparkSession.read.schema(self.blocks.schema).parquet(f"{self.path}/part={block_id}")
        return self.read[block_id]


def block_graph(
    edges: DataFrame, vertices: DataFrame | None = None, p: int = 4, layout: str = "2d", cuts: str | Cuts = "uniform", order: str = "row", directed: bool = False, keep: bool = False
) -> BlockedGraph:
    """Assign every directed edge to one block.

    ``2d``: the same cuts on both axes. ``1d``: destinations are cut, every row of blocks is one stripe wide, so a
    destination's sum needs no merge across blocks. ``keep`` writes the blocks to the shared folder first, in buckets of the
    source, so that a round moves attributes to the edges and never edges.
    """
    if order not in ORDERS:
        raise ValueError(f"unknown block order {order!r}")
    if layout not in ("2d", "1d"):
        raise ValueError(f"unknown layout {layout!r}")
    chosen = cuts if isinstance(cuts, Cuts) else cutting.symmetric(edges, p, cuts)
    both = edges if directed else symmetric(edges)
    row = chosen.stripe("src") if layout == "2d" else F.lit(0)
    rest = [c for c in both.columns if c not in ("src", "dst")]
    placed = both.select(row.alias("row"), chosen.stripe("dst").alias("col"), "src", "dst", *rest)
    blocks = placed.select("row", "col", ORDERS[order](F.col("row"), F.col("col"), chosen.p).cast("long").alias("block_id"), "src", "dst", *rest)
    if keep:
        blocks = bucketed(blocks, "src", order=["src", "dst"])
    nodes = (vertices if vertices is not None else endpoints(edges)).select("id", chosen.stripe("id").alias("stripe"))
    return BlockedGraph(blocks, manifest_of(blocks, chosen, layout), nodes, chosen, layout, keep)


def sizes_of(blocks: DataFrame) -> DataFrame:
    """The part of the manifest that planning needs: a row per block with its place, edges and bytes."""
    return blocks.groupBy("block_id", "row", "col").agg(F.count("*").alias("n_edges")).withColumn("bytes", F.col("n_edges") * EDGE_BYTES)


def block_folders(edges: DataFrame, cuts: Cuts) -> BlockedGraph:
    """Blocks of directed edges as they are, each in a folder of its own: the edges are shuffled once, and a list of several blocks is read
    from where they lie. The manifest has places and sizes only."""
    path = fresh_path(edges.sparkSession, "blocks")
    at = edges.select(cuts.stripe("src").alias("row"), cuts.stripe("dst").alias("col"), F.col("src").cast("long"), F.col("dst").cast("long"))
    rows = at.select("row", "col", (F.col("row") * cuts.p + F.col("col")).cast("long").alias("block_id"), "src", "dst").withColumn("part", F.col("block_id"))
    rows.repartition(cuts.p**2, "part").sortWithinPartitions("part", "src", "dst").write.partitionBy("part").parquet(path)
    blocks = edges.sparkSession.read.schema("row int, col int, block_id long, src long, dst long").parquet(path).drop("part")
    return BlockedGraph(blocks, stored(sizes_of(blocks), "manifest"), None, cuts, path=path)


def placed(links: DataFrame, cuts: Cuts | None) -> BlockedGraph:
    """A graph over links (a, b) as they are, for programs whose edges change with the rounds. Without cuts it is one block."""
    row, col = (cuts.stripe("a"), cuts.stripe("b")) if cuts else (F.lit(0), F.lit(0))
    blocks = links.select(row.alias("row"), col.alias("col"), F.col("a").alias("src"), F.col("b").alias("dst"))
    blocks = blocks.withColumn("block_id", (F.col("row") * (cuts.p if cuts else 1) + F.col("col")).cast("long"))
    return BlockedGraph(blocks, sizes_of(blocks), None, cuts)


def manifest_of(blocks: DataFrame, cuts: Cuts, layout: str = "2d") -> DataFrame:
    """A row per block that has edges: its place, id ranges and sizes. At most p^2 rows."""
    spans = cuts.table(blocks.sparkSession)
    counted = blocks.groupBy("block_id", "row", "col").agg(
        F.count("*").alias("n_edges"), F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst")
    )
    cols = F.broadcast(spans.select(F.col("stripe").alias("col"), F.col("lo").alias("dst_lo"), F.col("hi").alias("dst_hi")))
    rows = F.broadcast(spans.select(F.col("stripe").alias("row"), F.col("lo").alias("src_lo"), F.col("hi").alias("src_hi")))
    joined = counted.join(cols, "col")
    joined = joined.join(rows, "row") if layout == "2d" else joined.withColumns({"src_lo": F.lit(cuts.bounds[0]).cast("long"), "src_hi": F.lit(cuts.bounds[-1]).cast("long")})
    return joined.select("block_id", "row", "col", "src_lo", "src_hi", "dst_lo", "dst_hi", "n_edges", "n_src", "n_dst", (F.col("n_edges") * EDGE_BYTES).alias("bytes"))


def coverage(graph: BlockedGraph, edges: DataFrame) -> DataFrame:
    """One row: edges in blocks, edges expected, edges that are missing or extra. The last two are equal to 0 and the first two agree."""
    both = symmetric(edges).select("src", "dst")
    there = graph.blocks.select("src", "dst")
    sizes = graph.blocks.agg(F.count("*").alias("in_blocks")).crossJoin(both.agg(F.count("*").alias("expected")))
    missing = both.exceptAll(there).agg(F.count("*").alias("missing"))
    extra = there.exceptAll(both).agg(F.count("*").alias("extra"))
    return sizes.crossJoin(missing).crossJoin(extra)
