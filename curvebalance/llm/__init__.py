"""Operators of a large training-data pipeline, on tables of documents, pages and embeddings."""
