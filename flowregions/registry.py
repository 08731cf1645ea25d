"""Where queries are registered by name, with their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def register(name: str, make: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = make
    if sql:
        ORACLES[name] = sql


def rounded(frame: DataFrame, digits: int = 4, **more: int) -> DataFrame:
    """All doubles rounded alike, as in the SQL."""
    return frame.select(*[F.round(c, more.get(c, digits)).alias(c) if t == "double" else F.col(c) for c, t in frame.dtypes])
