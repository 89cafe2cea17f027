"""The register of named plans."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Plan = Callable[[SparkSession, str], DataFrame]
PLANS: dict[str, Plan] = {}
SQL: dict[str, str] = {}


def plan(sql: str | None = None, name: str | None = None) -> Callable[[Plan], Plan]:
    """Registers a plan under its function's name, with DuckDB SQL for its result where SQL can express it."""

    def register(make: Plan) -> Plan:
        key = name or make.__name__
        if key in PLANS:
            raise ValueError(f"{key} is registered twice")
        PLANS[key] = make
        if sql:
            SQL[key] = sql
        return make

    return register
