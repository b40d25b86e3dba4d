"""Bounded-context evidence graph on Spark: immutable content-addressed capsules, a disposable
derived interpretation, and bounded, authorized context retrieval."""
