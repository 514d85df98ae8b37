"""Registry of the engine's own queries and of their DuckDB oracles."""

from __future__ import annotations

from . import comparison, learning, pairing, profiling, published, streams, surround, transformed  # noqa: F401  each registers its queries
from .learning import flagship  # noqa: F401
from .registry import ORACLES, QUERIES


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict:
    return {name: sql() if callable(sql) else sql for name, sql in ORACLES.items()}
