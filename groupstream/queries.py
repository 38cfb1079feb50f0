"""All queries by name, and the SQL of those that SQL can express."""

from __future__ import annotations

from .plans import catalog_evaluation, catalog_index, catalog_influence, catalog_model, catalog_operators, catalog_sampling

CATALOGS = [catalog_model, catalog_sampling, catalog_influence, catalog_index, catalog_evaluation, catalog_operators]


def queries() -> dict:
    return {name: f for c in CATALOGS for name, f in c.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for c in CATALOGS for name, sql in c.SQL.items()}
