"""Registry of queries over the given tables and of the SQL that checks them."""

from __future__ import annotations

import importlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
#: Modules that register queries when imported.
MODULES: tuple[str, ...] = ("pathlift.plans.edges", "pathlift.plans.augmentation", "pathlift.plans.searching", "pathlift.plans.relational", "pathlift.plans.streams", "pathlift.plans.studies", "pathlift.plans.estimation", "pathlift.plans.comparison", "pathlift.plans.surroundings")


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    """Registers a function of (spark, sf_dir) under a name, with its SQL if it has any."""

    def register(function: Query) -> Query:
        QUERIES[name] = function
        if sql:
            ORACLES[name] = sql
        return function

    return register


def load_all() -> None:
    for module in MODULES:
        importlib.import_module(module)
