"""Structured Streaming over the events: windows, late rows, replays, scope-local projection."""
