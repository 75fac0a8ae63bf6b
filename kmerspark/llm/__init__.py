"""Training-data operators: packing, search, sharding, deduplication, toxicity and mixing.

Nothing outside this subpackage imports it.
"""
