"""Training-data operators: deduplication, scoring, packing, tokens, privacy and URL filters.

Nothing outside this subpackage imports it.
"""
