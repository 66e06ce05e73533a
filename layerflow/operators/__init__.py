"""Operators on graphs and embeddings."""
