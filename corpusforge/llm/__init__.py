"""Training-data operators: dedup, tokenising, PII, search, quality, packing, URLs, licences.

Nothing outside this subpackage imports it.
"""
