"""Where queries register: a name, a function of the workload, and SQL where it can express the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from .workload import Workload, workload

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def add(name: str, run: Callable[[Workload], DataFrame], oracle: str | None = None) -> None:
    QUERIES[name] = lambda spark, sf_dir: run(workload(spark, sf_dir))
    if oracle is not None:
        ORACLES[name] = oracle
