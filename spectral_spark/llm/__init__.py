"""Training-data operators: deduplication, filtering, counting, packing, archives and search.

Nothing outside this subpackage imports it.
"""
