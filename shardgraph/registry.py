"""Name -> query and name -> SQL twin, gathered from the modules that define them."""

from __future__ import annotations

from collections.abc import Callable
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession


class Entry(NamedTuple):
    run: Callable[[SparkSession, str], DataFrame]
    sql: str | None


class Registry(dict[str, Entry]):
    def query(self, name: str, sql: str | None = None):
        """Decorator: registers ``f(spark, sf_dir)`` under ``name`` with its DuckDB twin."""

        def put(f):
            if name in self:
                raise ValueError(f"{name} is registered twice")
            self[name] = Entry(f, sql)
            return f

        return put

    def queries(self) -> dict[str, Callable[[SparkSession, str], DataFrame]]:
        return {k: e.run for k, e in self.items()}

    def oracles(self) -> dict[str, str]:
        return {k: e.sql for k, e in self.items() if e.sql}


CORE = Registry()


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
