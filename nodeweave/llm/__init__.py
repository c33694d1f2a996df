"""Operators of a training-data pipeline: packing, token output, BPE, URL and HTML filters,
near-duplicates, toxicity, exact search, personal data and media columns."""
