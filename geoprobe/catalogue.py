"""All queries over the given tables by name, and their SQL twins."""

from .plans import geography, interventions, measuring, probing, vector_tests

PARTS = (geography, measuring, vector_tests, interventions, probing)
QUERIES: dict = {name: query for part in PARTS for name, query in part.QUERIES.items()}
ORACLE_SQL: dict[str, str] = {name: sql for part in PARTS for name, sql in part.ORACLE_SQL.items()}
