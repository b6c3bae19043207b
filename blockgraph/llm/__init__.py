"""Training-data operators: decontamination, toxicity, language models, sharding, joins, counts, archives, media.

Nothing outside this subpackage imports it.
"""
