"""All registered queries and their SQL twins."""

from __future__ import annotations

from . import experiments, extras, model, relational, streams, vectors

MODULES = (model, vectors, relational, streams, experiments, extras)


def queries() -> dict:
    return {k: f for m in MODULES for k, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for m in MODULES for k, s in m.SQL.items()}
