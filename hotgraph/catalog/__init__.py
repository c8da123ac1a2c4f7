"""Every method, measure, workload and operator as a query, with DuckDB SQL where SQL expresses it."""

from __future__ import annotations

from hotgraph.catalog import core, graphs, measures, relational, scalar, streams, udfs, updates, workloads
from hotgraph.catalog.base import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "core", "graphs", "measures", "relational", "scalar", "streams", "udfs", "updates", "workloads"]
