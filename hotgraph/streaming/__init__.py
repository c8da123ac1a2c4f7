"""Structured Streaming: serving from a live stream, windows, late rows, joins and per-vertex state."""
