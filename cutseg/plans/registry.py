"""All queries of the engine proper."""

from cutseg.plans import methods, relational, workloads  # noqa: F401  (they register)

QUERIES, ORACLE_SQL = methods.QUERIES, methods.ORACLE_SQL
