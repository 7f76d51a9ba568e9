"""Queries over the given tables and their oracles, one module per part of the inventory."""

from diversify.queries import experiments, methods, surroundings

MODULES = (methods, surroundings, experiments)
QUERIES: dict = {k: v for m in MODULES for k, v in m.QUERIES.items()}
SQL: dict = {k: v for m in MODULES for k, v in m.SQL.items()}
