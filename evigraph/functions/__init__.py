"""Expressions: canonical content, ids, times."""
