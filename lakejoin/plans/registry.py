"""Queries by name, with their oracles."""

from __future__ import annotations

QUERIES: dict = {}
#: SQL text, or a function that writes it when asked.
ORACLES: dict = {}


def query(name: str, oracle=None):
    def keep(fn):
        if name in QUERIES:
            raise ValueError(f"two queries named {name}")
        QUERIES[name] = fn
        if oracle is not None:
            ORACLES[name] = oracle
        return fn

    return keep
