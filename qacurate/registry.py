"""Query registry: a query and its oracle SQL are declared together, so the pair cannot drift."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


class Registry:
    def __init__(self) -> None:
        self.queries: dict[str, Query] = {}
        self.oracles: dict[str, str] = {}

    def add(self, name: str, oracle: str | None = None) -> Callable[[Query], Query]:
        def keep(fn: Query) -> Query:
            if name in self.queries:
                raise ValueError(f"query {name} is declared twice")
            self.queries[name] = fn
            if oracle is not None:
                self.oracles[name] = oracle
            return fn

        return keep


REGISTRY = Registry()
query = REGISTRY.add


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One of the given tables; any path that Spark can open."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{table}.parquet")
