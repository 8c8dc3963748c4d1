"""All queries of the engine, each beside its SQL."""

from __future__ import annotations

from . import experiments, relational, retrieval, signals, supply

ALL = retrieval.TABLE | supply.TABLE | signals.TABLE | experiments.TABLE | relational.TABLE


def queries() -> dict:
    return {k: f for k, (f, _) in ALL.items()}


def oracle_sql() -> dict[str, str]:
    return {k: sql for k, (_, sql) in ALL.items() if sql}


def entry(spark, sf_dir: str):
    return retrieval.table(spark, sf_dir)
