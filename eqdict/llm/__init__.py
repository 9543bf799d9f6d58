"""Training-data operators: filtering, deduplication, counting, mixing and packing of documents.

Nothing outside this subpackage imports it.
"""
