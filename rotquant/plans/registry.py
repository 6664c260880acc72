"""All queries of the quantizers with their SQL."""

from __future__ import annotations

from . import reports, tasks  # noqa: F401  (they register their queries)
from .workloads import QUERIES, SQL


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return {k: v if isinstance(v, str) else v() for k, v in SQL.items()}
