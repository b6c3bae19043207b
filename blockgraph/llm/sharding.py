"""Operator 4: proportional stratified interleaving into shards.

Rows are shuffled within their source by a seeded hash and ranked; (2 rank - 1) / (2 n) places a row of a source
with n rows on the unit interval. Sorting all sources by that place interleaves them in proportion, and cutting
the order into equal runs gives shards whose counts differ by one at most and whose mixtures match (law ``rows``).
The method has no groups that must stay together, so copies of a text are spread like other rows.

No rank is taken by one task per source: rows are dealt into buckets by ranges of the hash (and later by ranges
of the place), bucket counts give offsets, and only the rows of one bucket are sorted together. A source that
holds a third of the table is cut into as many pieces as there are buckets.

Defined cases: a null source is a stratum of its own; a null text has size 1 and CRC 0; equal rows take
neighbouring places in any order; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .scratch import stored

SEED = 20240229
#: Rows aimed at in a bucket, and the most buckets: their offsets are the only table that is broadcast.
BUCKET_ROWS, MAX_BUCKETS = 1024, 1 << 16


def bucket_bits(n_rows: int) -> int:
    return (max(1, min(MAX_BUCKETS, -(-n_rows // BUCKET_ROWS))) - 1).bit_length()


def place_rows(rows: DataFrame, stratum: str, order: list[str]) -> DataFrame:
    """``rows`` (with a hash column ``h``) plus ``rank`` in its stratum from 1 and ``place`` in (0, 1)."""
    bits = bucket_bits(rows.count())
    rows = rows.withColumn("bucket", F.shiftright("h", 64 - bits) if bits else F.lit(0).cast("long"))
    counts = rows.groupBy(stratum, "bucket").agg(F.count("*").alias("n"))
    whole = W.partitionBy(stratum)
    offsets = counts.select(stratum, "bucket", (F.sum("n").over(whole.orderBy("bucket")) - F.col("n")).alias("before"), F.sum("n").over(whole).alias("total"))
    within = W.partitionBy(stratum, "bucket").orderBy("h", *order)
    ranked = rows.join(offsets, [stratum, "bucket"]).withColumn("rank", F.col("before") + F.row_number().over(within))
    return ranked.withColumn("place", (2 * F.col("rank") - 1) / (2 * F.col("total"))).drop("bucket", "before", "total")


def interleave(placed: DataFrame, n_rows: int, order: list[str]) -> DataFrame:
    """``placed`` plus ``position``: 0, 1, ... in the order of ``place``."""
    buckets = 1 << bucket_bits(n_rows)
    placed = placed.withColumn("bucket", F.floor(F.col("place") * buckets))
    counts = placed.groupBy("bucket").agg(F.count("*").alias("n"))
    offsets = counts.select("bucket", (F.sum("n").over(W.orderBy("bucket")) - F.col("n")).alias("before"))
    within = W.partitionBy("bucket").orderBy("place", *order)
    # At most MAX_BUCKETS rows of two numbers.
    return placed.join(F.broadcast(offsets), "bucket").withColumn("position", F.col("before") + F.row_number().over(within) - 1).drop("bucket", "before")


def stratified_shards(docs: DataFrame, shards: int = 16, seed: int = SEED, stratum: str = "source") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard, and the row's stratum, rank and place."""
    text = F.coalesce(F.col("text"), F.lit(""))
    base = docs.select(
        "doc_id",
        F.when(F.col(stratum).isNull(), "-").otherwise(F.concat(F.lit("+"), F.col(stratum).cast("string"))).alias("stratum"),
        (F.octet_length(text) + 1).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
    ).withColumn("h", F.xxhash64(F.lit(seed), "doc_id", "size", "text_crc32"))
    order = ["stratum", "h", "doc_id", "size", "text_crc32"]
    placed = stored(place_rows(base, "stratum", order[2:]), "shard-places")
    n = placed.count()
    laid = interleave(placed, n, order).withColumn("shard", F.expr(f"position * {shards} div {max(n, 1)}"))
    first = F.expr(f"(shard * {max(n, 1)} + {shards - 1}) div {shards}")
    return laid.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), (F.col("position") - first).alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"), "stratum", "rank", "place",
    )


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return stratified_shards(docs).select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")
