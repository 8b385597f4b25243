"""Training-data operators: tokens, packing, cleaning, mixing, search and deduplication.

Nothing outside this subpackage imports it; ``queries.py`` lists its queries.
"""
