"""Training-data operators: media, packing, deduplication, tokenization, scoring and sharding of documents.

Nothing else in the library imports this subpackage.
"""
