"""Training-data operators: mixing, tokenising, deduplication, filtering.

Nothing outside this subpackage imports it.
"""
