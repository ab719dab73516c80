"""Training-data operators: deduplication, tokenization, mixing, extraction.

Nothing outside this subpackage imports it.
"""
