"""All queries of the engine and their DuckDB SQL."""

from __future__ import annotations

from kmfold.plans import comparison_queries, experiment_queries, method_queries, relational_queries
from kmfold.plans.method_queries import flagship

QUERIES = {**method_queries.Q, **experiment_queries.Q, **comparison_queries.Q, **relational_queries.Q}
ORACLE_SQL = {**method_queries.SQL, **experiment_queries.SQL, **comparison_queries.SQL, **relational_queries.SQL}

__all__ = ["ORACLE_SQL", "QUERIES", "flagship"]
