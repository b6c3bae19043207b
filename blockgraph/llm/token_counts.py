"""Operator 6: token counts through a digest cache.

A stored count belongs to the SHA-256 of the content and to a version digest of the tokenizer (file bytes and
encoding options). Digests of the input are looked up in the cache; only distinct contents that it lacks are
encoded, once each, and appended. The answer is then read from the cache alone.

Digests are shuffled, texts only where they must be: a missing content that one row alone holds is encoded where it lies.
Contents that several rows hold are brought together by digest, once per batch at most, so that a text which fills a third of the
table costs no task more than its batches. A bitmap of fixed size tells the two apart; what it cannot tell goes the long way.

Defined cases: a null text is empty (0 tokens); equal texts share a count; several appends of one digest
(after concurrent runs) count once; a text of any length is encoded whole; an empty table adds nothing to the cache; no column but
``doc_id`` and ``text`` is read, whatever others are called.
"""

from __future__ import annotations

import hashlib
import os
from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .lossy import MOST_FILTERED, bitmap, held
from .scratch import scratch_path, stored
from .text import rows_of, slices, utf8

LIMIT = 1024
CACHE_SCHEMA = "digest binary, n_bytes bigint, n_tokens bigint, version string"
_ENCODE_BYTES = 2 << 20


def tokenizer_version(path: str) -> str:
    """Digest of the tokenizer's file and of the options that change counts."""
    with open(path, "rb") as f:
        return hashlib.sha256(f.read() + b"|plain|no added tokens|no truncation|no padding").hexdigest()


@cache
def load_counter(path: str):
    """Once per worker: list of texts -> list of counts, by the library that the kind of file belongs to."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda texts: [len(x) for x in model.encode(texts, num_threads=1)]
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(path)
    model.no_truncation()
    model.no_padding()
    return lambda texts: [len(x) for x in model.encode_batch_fast(texts, add_special_tokens=False)]


def distinct_in_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each digest once per batch."""
    for batch in batches:
        keys = rows_of(batch, "digest").to_pylist()
        seen: set[bytes] = set()
        first = [i for i, k in enumerate(keys) if not (k in seen or seen.add(k))]
        yield batch if len(first) == len(keys) else batch.take(pa.array(first))


def encoder(path: str, version: str):
    """Cache rows of (digest, text) rows; of equal digests in a row the first one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count, last = None, None
        for batch in batches:
            count = count or load_counter(path)
            keys = rows_of(batch, "digest").to_pylist()
            fresh = [i for i, k in enumerate(keys) if k != (keys[i - 1] if i else last)]
            last = keys[-1] if keys else last
            batch = batch.take(pa.array(fresh, pa.int64()))
            texts = rows_of(batch, "text")
            _, offs = utf8(texts)
            for i, j in slices(offs, _ENCODE_BYTES):
                part = texts.slice(i, j - i)
                yield pa.RecordBatch.from_arrays(
                    [rows_of(batch, "digest").slice(i, j - i), pc.cast(pc.binary_length(part), pa.int64()), pa.array(count(part.to_pylist()), pa.int64()), pa.array([version] * (j - i))],
                    ["digest", "n_bytes", "n_tokens", "version"],
                )

    return run


def read_cache(spark: SparkSession, cache: str, version: str) -> DataFrame:
    """digest, n_bytes, n_tokens of one tokenizer version; an absent cache is empty."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(cache)
    if not folder.getFileSystem(spark._jsc.hadoopConfiguration()).exists(folder):
        return spark.createDataFrame([], "digest binary, n_bytes bigint, n_tokens bigint")
    return spark.read.schema(CACHE_SCHEMA).parquet(cache).where(F.col("version") == version).groupBy("digest").agg(F.min("n_bytes").alias("n_bytes"), F.min("n_tokens").alias("n_tokens"))


def _digested(docs: DataFrame) -> DataFrame:
    content = F.coalesce(F.col("text"), F.lit(""))
    return docs.select("doc_id", F.unhex(F.sha2(content.cast("binary"), 256)).alias("digest"), content.alias("text"))


def _passing(where: Callable[[np.ndarray], np.ndarray]):
    """(digest, text) of the rows whose hash ``h`` passes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept = batch.filter(pa.array(where(rows_of(batch, "h").to_numpy(zero_copy_only=False))))
            yield kept.select(["digest", "text"])

    return run


def extend_cache(docs: DataFrame, tokenizer_path: str, cache: str) -> tuple[int, int]:
    """Encode what the cache at ``cache`` lacks of these documents, and append it. Returns the distinct contents and those that were missing."""
    spark = docs.sparkSession
    version = tokenizer_version(tokenizer_path)
    rows = _digested(docs)
    known = read_cache(spark, cache, version).select("digest", F.lit(True).alias("hit"))
    looked_up = rows.groupBy("digest").agg(F.count("*").alias("n")).join(known, "digest", "left")
    looked_up = stored(looked_up.select("digest", "n", "hit", F.xxhash64("digest").alias("h")), "digests")
    counts = looked_up.agg(F.count("*").alias("all"), F.count_if(F.col("hit").isNull()).alias("missing"), F.count_if(F.expr("hit is null and n > 1")).alias("several")).first()
    if not counts.missing:
        return counts["all"], 0
    missing = looked_up.where("hit is null")
    hashed = rows.select("digest", "text", F.xxhash64("digest").alias("h"))
    if counts.missing <= MOST_FILTERED:
        lacking = spark.sparkContext.broadcast(bitmap(missing.select("h"), counts.missing))
        several = spark.sparkContext.broadcast(bitmap(missing.where("n > 1").select("h"), counts.several))
        alone = hashed.mapInArrow(_passing(lambda h: held(lacking.value, h) & ~held(several.value, h)), "digest binary, text string")
        alone.mapInArrow(encoder(tokenizer_path, version), CACHE_SCHEMA).write.mode("append").partitionBy("version").parquet(cache)
        hashed = hashed.mapInArrow(_passing(lambda h: held(several.value, h)), "digest binary, text string")
    # Contents of several rows, and those that the bitmap cannot tell from them.
    shared = hashed.select("digest", "text").mapInArrow(distinct_in_batches, "digest binary, text string")
    shared = shared.join(missing.select("digest"), "digest", "left_semi").repartition("digest").sortWithinPartitions("digest")
    shared.mapInArrow(encoder(tokenizer_path, version), CACHE_SCHEMA).write.mode("append").partitionBy("version").parquet(cache)
    return counts["all"], counts.missing


def count_tokens(docs: DataFrame, tokenizer_path: str, cache: str) -> DataFrame:
    """doc_id, n_bytes, n_tokens of every document; the cache at ``cache`` is extended by what it lacked."""
    spark = docs.sparkSession
    extend_cache(docs, tokenizer_path, cache)
    # A plain scan on both sides lets adaptive execution split the partition of a digest that fills the table.
    counts = stored(read_cache(spark, cache, tokenizer_version(tokenizer_path)), "token-counts")
    return _digested(docs).select("doc_id", "digest").join(counts, "digest").select("doc_id", "n_bytes", "n_tokens")


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two loads, as a cache sees them: a part of the table comes first, then the whole table, which finds that part in the cache. The result
    covers every row."""
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    path, cache = public_tokenizers.path("byte_bpe_50k.json"), scratch_path(spark, "token-cache")
    extend_cache(docs.where("pmod(crc32(cast(cast(doc_id as string) as binary)), 8) = 0"), path, cache)
    return count_tokens(docs, path, cache).withColumn("over_limit", F.col("n_tokens") > LIMIT)
