"""Training-data operators on text tables: deduplication, filtering, scoring, tokenisation.

Nothing outside this subpackage imports it.
"""
