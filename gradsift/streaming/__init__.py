"""Structured Streaming forms of rating, selection and trace windows."""
