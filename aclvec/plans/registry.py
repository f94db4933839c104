"""The catalogue: named queries and, where SQL can express them, their DuckDB text."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    """Registers a function of (spark, sf_dir)."""

    def put(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def r6(c) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6)


def big(c) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("long")


def violations(spark, counts: dict[str, int | float | bool]) -> DataFrame:
    """check_name, violations: a boolean is 1 where it fails."""
    rows = [(k, int(not v) if isinstance(v, bool) else int(v)) for k, v in counts.items()]
    return spark.createDataFrame(rows, "check_name string, violations long")


def zeros(*names: str) -> str:
    return "SELECT * FROM (VALUES " + ", ".join(f"('{n}', 0::BIGINT)" for n in names) + ") t(check_name, violations)"
