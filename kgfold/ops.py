"""Registry of queries and their oracles (everything but the text operators)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


def _modules():
    from kgfold.plans import relational, workloads

    return [workloads, relational]


def queries() -> dict[str, Query]:
    found: dict[str, Query] = {}
    for m in _modules():
        found |= m.queries()
    return found


def oracle_sql() -> dict[str, str]:
    found: dict[str, str] = {}
    for m in _modules():
        found |= m.oracle_sql()
    return found
