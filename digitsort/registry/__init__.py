"""Registered queries and their SQL, by area; see ``all_queries`` and ``all_sql``."""

from . import apps, measures_q, planning, relational, sorting, streams_q

_AREAS = (sorting, planning, measures_q, apps, relational, streams_q)


def all_queries() -> dict:
    return {k: v for a in _AREAS for k, v in a.QUERIES.items()}


def all_sql() -> dict:
    return {k: v for a in _AREAS for k, v in a.SQL.items()}
