"""Collects the query and oracle tables of the engine's modules."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


def _modules() -> list:
    from nbflow.plans import catalogue, compiled, evaluate, eventlog, mine, storage, surface
    from nbflow.streaming import twins

    return [eventlog, catalogue, surface, mine, evaluate, storage, compiled, twins]


def queries() -> dict[str, Query]:
    found: dict[str, Query] = {}
    for module in _modules():
        found |= module.QUERIES
    return found


def oracle_sql() -> dict[str, str]:
    from nbflow.plans import corpus_sql

    found: dict[str, str] = dict(corpus_sql.SQL)
    for module in _modules():
        found |= module.ORACLES
    return found
