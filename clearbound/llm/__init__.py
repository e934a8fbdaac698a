"""Operators of a training-data pipeline: toxicity, substring and near-duplicate
removal, tokenisation, quality and language models, packing, sharding, search.

Nothing outside this package imports it; ``queries.py`` holds the registered queries.
"""
