"""Registry of the engine's queries: each has a Spark form and, where SQL can say it, an oracle with the same columns."""

from taskmap.queries import experiments, mappers, measures, relational, steps

MODULES = (steps, measures, mappers, relational, experiments)
QUERIES = {name: query for module in MODULES for name, query in module.QUERIES.items()}
SQL = {name: sql for module in MODULES for name, sql in module.SQL.items()}

flagship = mappers.flagship
