"""Registry of the queries of the near-duplicate methods."""

from __future__ import annotations

import inspect
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from neardup.session import ship_package


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters of near duplicates with a guaranteed least similarity, and each document's bound."""
    return queries()["bounded_clusters_075"](spark, sf_dir)


def _shipped(query: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship_package(spark)
        return query(spark, sf_dir)

    run.__name__, run.__doc__ = query.__name__, query.__doc__
    return run


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """All public functions (spark, d) of the workload modules."""
    from neardup.workloads import methods, relational

    found = {}
    for module in (methods, relational):
        for name, f in inspect.getmembers(module, inspect.isfunction):
            if f.__module__ == module.__name__ and not name.startswith("_") and list(inspect.signature(f).parameters) == ["spark", "d"]:
                found[name] = _shipped(f)
    return found


def oracle_sql() -> dict[str, str]:
    from neardup.workloads import methods_sql, relational

    return methods_sql.oracle_sql() | relational.oracle_sql()
