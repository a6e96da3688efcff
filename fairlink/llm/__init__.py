"""Operators of a training-data pipeline: fingerprints, quality, toxicity, shards, secrets,
tokens, page text, packing, repeated passages and near duplicates.

Nothing else in the library imports this subpackage.
"""
