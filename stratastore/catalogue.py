"""All queries of the engine and their SQL."""

from __future__ import annotations

from .queries import ORACLES, QUERIES, Query
from .queries import core, costs, relational  # noqa: F401  they add their queries


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
