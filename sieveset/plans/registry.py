"""All registered queries and the SQL that checks them."""

from __future__ import annotations

from sieveset.streaming import queries as streams

from . import catalog_methods, catalog_operators

_CATALOGUES = (catalog_methods, catalog_operators, streams)


def queries() -> dict:
    return {name: f for c in _CATALOGUES for name, f in c.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for c in _CATALOGUES for name, sql in c.ORACLES.items()}
