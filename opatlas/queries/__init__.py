"""Every method as a named query over the given tables, with its SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

Run = Callable[[SparkSession, str], DataFrame]


@dataclass
class Catalog:
    """Queries of one part of the library and their SQL."""

    runs: dict[str, Run]
    sql: dict[str, str]

    def __init__(self) -> None:
        self.runs, self.sql = {}, {}

    def query(self, sql: str | None = None) -> Callable[[Run], Run]:
        def add(run: Run) -> Run:
            self.runs[run.__name__] = run
            if sql:
                self.sql[run.__name__] = sql
            return run

        return add


def catalogs() -> list[Catalog]:
    from . import labels, mining, relational, serving, taxonomy

    return [m.CATALOG for m in (taxonomy, mining, labels, serving, relational)]
