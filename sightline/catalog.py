"""Names of all queries with their builders and SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Builder = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Builder] = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None) -> Callable[[Builder], Builder]:
    """Register a builder under its function's name, with the SQL that DuckDB answers alike, if there is one."""

    def put(f: Builder) -> Builder:
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return put


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turning counts of every test clip after proxy, windows, detector, tracker and repair."""
    return QUERIES["turning_counts_full"](spark, sf_dir)


from .plans import gates, measures, operators, repair, scenes, streams, studies, tracks, tuning, windows  # noqa: E402, F401
