"""File lists and scheduled reports: sorted list files in versioned directories."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_list(found: DataFrame, path: str, version: int, order: tuple[str, ...] = ("path",)) -> str:
    """A globally sorted list as text-safe CSV under a directory of its own; running it again replaces it."""
    at = f"{path}/version={version}"
    found.orderBy(*order).write.mode("overwrite").option("header", True).option("escape", '"').csv(at)
    return at
