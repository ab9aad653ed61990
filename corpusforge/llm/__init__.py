"""Training-data operators: counting, sharding, scanning, identifying, deduplicating and packing documents.

Nothing outside this subpackage imports it.
"""
