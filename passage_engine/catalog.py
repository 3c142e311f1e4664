"""Registry of queries: key to builder and DuckDB twin."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Query:
    build: Callable[[SparkSession, str], DataFrame]
    oracle: str | None = None


CATALOG: dict[str, Query] = {}


def register(key: str, oracle: str | None = None):
    """Decorator: enter a builder under its key."""

    def enter(build):
        if key in CATALOG:
            raise ValueError(f"two queries are called {key}")
        CATALOG[key] = Query(build, oracle)
        return build

    return enter


def load() -> dict[str, Query]:
    """The filled registry; importing an experiment's module registers its queries."""
    from .experiments import core, learned, speech, surface  # noqa: F401
    from .operators import relational  # noqa: F401
    from .streaming import live  # noqa: F401

    return CATALOG
