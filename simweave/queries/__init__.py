"""Query registry: each key has a Spark callable and, where SQL can express it, an oracle."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register a query function under a key, with its oracle."""

    def keep(f: Callable) -> Callable:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def load() -> tuple[dict[str, Callable], dict[str, str]]:
    """All registered queries and oracles."""
    import importlib

    for part in ("inference", "hashes", "joins", "studies", "relational", "streams"):
        importlib.import_module(f"simweave.queries.{part}")

    return QUERIES, ORACLES
