"""All queries of the library."""

from metricblock.queries import distances, figures, methods, relational, streams, udfs  # noqa: F401
from metricblock.queries.registry import ORACLE_SQL, QUERIES

__all__ = ["ORACLE_SQL", "QUERIES"]
