"""All registered queries."""

from privgrove.queries import experiments, methods, relational, whole_trees  # noqa: F401
from privgrove.queries.base import QUERIES, SQL

__all__ = ["QUERIES", "SQL"]
