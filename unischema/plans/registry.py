"""All core queries and their DuckDB forms, by name."""

from __future__ import annotations

from unischema.plans import experiment_queries, integration_queries, method_queries, operator_queries  # noqa: F401  the import registers

ALL = dict(method_queries.QUERIES)

QUERIES = {name: function for name, (function, _) in ALL.items()}
ORACLES = {name: sql for name, (_, sql) in ALL.items() if sql is not None}
