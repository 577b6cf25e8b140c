"""Operators for large text corpora, and the registered queries over the given tables."""
