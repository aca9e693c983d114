"""Training-data operators: PII, page text, packing, quality, dedup, tokens and URL filters.

Nothing outside this subpackage imports it.
"""
