"""Training-data operators: dedup, archives, token files, classifier, counts,
joins, audio columns, piece encoding, packing and exact top-k search.

Nothing outside this folder imports it; ``queries`` holds the registry.
"""
