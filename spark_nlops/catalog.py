"""All driver queries of the natural-language operators, with the SQL that recomputes them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .relational import surround
from .workloads import operators_catalog, studies

Query = Callable[[SparkSession, str], DataFrame]
MODULES = (operators_catalog, studies, surround)


def queries() -> dict[str, Query]:
    return {k: f for m in MODULES for k, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: q for m in MODULES for k, q in m.SQL.items()}
