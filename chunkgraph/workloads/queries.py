"""All driver checks of the graph engine."""

from __future__ import annotations

from . import around, graph_checks, set_checks  # noqa: F401
from .registry import ORACLES, QUERIES


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
