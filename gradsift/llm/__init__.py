"""Corpus operators for language-model training data.

Nothing outside this folder imports it; the folder can be removed as a whole.
"""
