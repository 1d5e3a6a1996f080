"""Training-data operators: deduplication, identification, privacy, placement, tokens.

Nothing outside this subpackage imports it.
"""
