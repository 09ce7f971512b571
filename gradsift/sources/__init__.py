"""Corpora over the given tables, and sinks for ratings and subsets."""
