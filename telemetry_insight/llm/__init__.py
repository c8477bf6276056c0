"""Training-data operators: deduplication, filtering, encoding, sharding, archives and joins.

Nothing outside this subpackage imports it.
"""
