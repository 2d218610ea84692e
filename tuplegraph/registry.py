"""All registered queries of the engine, with the SQL that checks them."""

from __future__ import annotations

from .plans import registered, registered2, registered3, registered4, registered5  # noqa: F401  the later ones add to the tables of the first


def queries() -> dict:
    return dict(registered.QUERIES)


def oracle_sql() -> dict:
    return dict(registered.SQL)
