"""Policies, the serving session, replayed workloads and the cost model."""
