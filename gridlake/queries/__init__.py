"""Registry of the grid engine's queries and their DuckDB counterparts."""

from gridlake.queries import methods, relational, workloads  # noqa: F401
from gridlake.queries.registry import ORACLES, QUERIES


def queries():
    return QUERIES


def oracle_sql():
    return ORACLES
