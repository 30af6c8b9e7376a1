"""The corpus operators' queries and SQL, by name."""

from taskmap.llm import bpe, merkle, mixing, neighbours, parity, quality, suffixes, tokencount, toxicity, windows

MODULES = (bpe, mixing, toxicity, merkle, quality, tokencount, suffixes, neighbours, windows, parity)
QUERIES = {name: query for module in MODULES for name, query in module.QUERIES.items()}
SQL = {name: sql for module in MODULES for name, sql in module.SQL.items()}
