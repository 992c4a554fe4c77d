"""Distributed operators on embeddings: expansion, aggregation, path store, balance."""
