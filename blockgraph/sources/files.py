"""Edge lists as text, block stores, and edges from any query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_edge_text(spark: SparkSession, path: str, sep: str = " ", comment: str = "#") -> DataFrame:
    """(src, dst[, w]) from lines of two or three fields; split files are read in parallel."""
    raw = spark.read.schema("src long, dst long, w double").option("sep", sep).option("comment", comment).option("mode", "PERMISSIVE").csv(path)
    return raw.where("src is not null and dst is not null")


def write_edge_text(edges: DataFrame, path: str, sep: str = " ") -> None:
    edges.write.option("sep", sep).csv(path)


def read_adjacency_text(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) from lines "src: dst dst ..."."""
    lines = spark.read.text(path).select(F.split("value", ":").alias("p")).where(F.size("p") == 2)
    return lines.select(F.trim(F.col("p")[0]).cast("long").alias("src"), F.explode(F.split(F.trim(F.col("p")[1]), r"\s+")).alias("d")).select("src", F.col("d").cast("long").alias("dst"))


def from_query(spark: SparkSession, sql: str, **args) -> DataFrame:
    """Edges from a statement that returns src and dst."""
    return spark.sql(sql, args=args or None)


def write_blocks(blocks: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Blocks in folders by row, sorted by column and source inside, so that scans of few stripes skip the rest."""
    ordered = blocks.repartition("row", "col").sortWithinPartitions("row", "col", "src", "dst")
    ordered.write.partitionBy("row").format(fmt).save(path)


def read_blocks(spark: SparkSession, path: str, rows: list[int] | None = None, fmt: str = "parquet") -> DataFrame:
    """A block store, or only some rows of blocks: the filter is on the folders."""
    blocks = spark.read.format(fmt).load(path)
    return blocks if rows is None else blocks.where(F.col("row").isin(rows))
