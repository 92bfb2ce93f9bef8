"""Operators of a training-data pipeline: near and exact duplicates, search,
quality, tokens, packing, page text and secrets.

Each operator module holds one DataFrame function with a general interface; the
thin registered queries live in ``queries.py`` and their SQL in ``oracles.py``.
"""
