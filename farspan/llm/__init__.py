"""Training-data operators: scoring, deduplication, filtering, packing and encoding of documents.

Nothing outside this subpackage imports it.
"""
