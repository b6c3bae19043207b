"""The queries of this subpackage and the SQL that DuckDB can check them by."""

from . import decontaminate, jaccard_join, language_id, language_model, media, sentencepiece_codec, sharding, token_counts, toxicity, warc

from .scratch import small_batches


def _bounded(query):
    """The query with small batches to its Python workers."""

    def run(spark, sf_dir):
        small_batches(spark)
        return query(spark, sf_dir)

    return run


QUERIES = {
    "op1_decontamination": decontaminate.op1_decontamination,
    "op2_toxicity": toxicity.op2_toxicity,
    "op3_language_model": language_model.op3_language_model,
    "op4_sharding": sharding.op4_sharding,
    "op5_jaccard_join": jaccard_join.op5_jaccard_join,
    "op6_token_counts": token_counts.op6_token_counts,
    "op7_language_id": language_id.op7_language_id,
    "op8_warc": warc.op8_warc,
    "op9_sentencepiece": sentencepiece_codec.op9_sentencepiece,
    "op10_telephony": media.op10_telephony,
}
QUERIES = {name: _bounded(query) for name, query in QUERIES.items()}
ORACLES = {
    "op1_decontamination": decontaminate.ORACLE,
    "op8_warc": warc.ORACLE,
}
