"""Degrees, hot sets, summaries, ranking loops, updates, measures and baselines."""
