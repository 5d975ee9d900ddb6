"""All queries of the catalogue."""

from featgreedy.queries import methods, paths, relational, workloads  # noqa: F401
from featgreedy.queries.registry import ORACLES, QUERIES  # noqa: F401
