"""Registered queries of the metadata engine and their SQL equivalents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def _all() -> dict:
    from fsmeta import catalog_events, catalog_snapshot

    return catalog_snapshot.R | catalog_events.R


def entry(spark: SparkSession) -> DataFrame:
    """Size and time quantiles per user of the large snapshot at the smallest scale."""
    return _all()["dd_quantiles_user"][0](spark, "/root/testdata/sf0.001")


def queries() -> dict:
    return {name: run for name, (run, _) in _all().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _all().items() if sql is not None}
