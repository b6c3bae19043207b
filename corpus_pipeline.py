"""From raw documents to pieces: language, toxicity, near duplicates, benchmark leaks, encoding.

Every stage takes what its predecessor kept, as reread Parquet, and all but the last return the columns of ``documents``.
Near duplicates are documents whose sets of 5-word shingles have a Jaccard similarity of 0.8 or more.

Defined cases: a document whose text is null or has no letter goes in the first stage; a null ``lang`` is not learned from; rows with a null
``doc_id`` stay through all stages (they are in no group of near duplicates, and no label is theirs); of rows that share a ``doc_id`` one stays;
texts of any length are taken whole; columns beside those of ``documents`` pass through the filtering stages, whatever their names; an
empty table gives an empty result, and one without labels is scored by the class prior.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockgraph.llm import decontaminate, jaccard_join, language_id, sentencepiece_codec, toxicity
from blockgraph.llm.scratch import small_batches, stored

SHINGLE_WORDS, SIMILAR_PERCENT = 5, 80


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents without a letter, and those of whose words no learned language has a fair share."""
    small_batches(spark)
    return language_id.keep_known(docs, language_id.fit(docs))


def not_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that score as toxic."""
    small_batches(spark)
    return toxicity.keep_clean(docs, toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the least document of each group of near duplicates."""
    small_batches(spark)
    return jaccard_join.keep_least(docs, SHINGLE_WORDS, SIMILAR_PERCENT)


def unleaked(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that hold a passage of the benchmark."""
    small_batches(spark)
    return decontaminate.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, piece_ids and their number."""
    small_batches(spark)
    import public_tokenizers

    return sentencepiece_codec.encode_pieces(docs, public_tokenizers.path("piece_bpe_32k.model")).withColumn("n_pieces", F.size("piece_ids"))


STAGES = [
    ("language_id", known_language),
    ("toxicity", not_toxic),
    ("near_duplicates", one_of_each),
    ("decontamination", unleaked),
    ("sentencepiece", pieces),
]

#: Trained models and seeded segmentations are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
