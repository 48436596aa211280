"""All queries of the library by name, and SQL that gives the same rows."""

from __future__ import annotations

from .queries import numeric, planning, surface  # noqa: F401 - modules register their queries
from .queries.registry import ORACLES, QUERIES


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)


flagship = planning.flagship
