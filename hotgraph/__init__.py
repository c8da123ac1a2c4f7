"""Ranking over evolving graphs on Spark: exact, reused or approximate answers over a stream of edge changes."""
