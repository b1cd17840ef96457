"""All queries of the reference's methods, and their DuckDB twins where SQL can express them."""

from avcurate.queries import relational, streams, workloads  # noqa: F401
from avcurate.queries.registry import ORACLES, QUERIES  # noqa: F401
