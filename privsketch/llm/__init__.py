"""Training-data operators: token counts, media columns, near-duplicates, scoring, filters, dedup, packing, encoding.

Nothing outside this subpackage imports it; ``queries.py`` holds the registered queries.
"""
