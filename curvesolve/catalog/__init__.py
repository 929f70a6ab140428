"""Registered queries of the library with their SQL counterparts, by area."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import faulting, grids, measured, solves, streams, surface, workloads

_AREAS = (grids, solves, faulting, workloads, measured, streams, surface)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for area in _AREAS for name, f in area.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for area in _AREAS for name, sql in area.SQL.items()}
