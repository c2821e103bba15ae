"""All registered queries of the engine, with DuckDB equivalents."""

from sparsegrid.queries import graphs, planning, products, relational, streams  # noqa: F401
from sparsegrid.queries.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
