"""Snapshot versions: publishing that may be repeated, differences, expiry."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fsmeta.plans import workspace

VALUES = ("type", "mode", "uid", "gid", "size", "atime", "ctime", "mtime", "fileset", "checksum", "project")


def publish(df: DataFrame, path: str, version: int, cut: dict[int, int] | None = None) -> None:
    """Write a version's records as a partition of their own; publishing it again replaces it.
    The manifest, written last, makes it visible and names the event sequence it covers."""
    spark = df.sparkSession
    df.write.mode("overwrite").parquet(f"{path}/data/version={version}")
    note = json.dumps({"version": version, "cut": {str(k): v for k, v in (cut or {}).items()}})
    spark.createDataFrame([(version, note)], "version long, note string").coalesce(1).write.mode("overwrite").json(f"{path}/manifest/v{version}")


def live(spark: SparkSession, path: str) -> int | None:
    """The newest version with a manifest."""
    try:
        return spark.read.schema("version long, note string").option("recursiveFileLookup", "true").json(f"{path}/manifest").agg(F.max("version")).first()[0]
    except Exception as e:  # no manifest yet
        if "PATH_NOT_FOUND" in str(e):
            return None
        raise


def cut(spark: SparkSession, path: str, version: int | None = None) -> dict[int, int]:
    """Per source, the last event sequence that a version (the newest by default) covers."""
    version = live(spark, path) if version is None else version
    if version is None:
        return {}
    row = spark.read.schema("version long, note string").json(f"{path}/manifest/v{version}").first()
    return {int(k): int(v) for k, v in json.loads(row["note"])["cut"].items()}


def expire(spark: SparkSession, path: str, keep: int = 2) -> list[int]:
    """Remove all but the newest ``keep`` published versions, each manifest before its data; gives the removed ones."""
    if live(spark, path) is None:
        return []
    have = sorted(r[0] for r in spark.read.schema("version long, note string").option("recursiveFileLookup", "true").json(f"{path}/manifest").select("version").distinct().toLocalIterator())
    gone = have[: max(0, len(have) - keep)]
    for v in gone:
        workspace.remove(spark, f"{path}/manifest/v{v}")
        workspace.remove(spark, f"{path}/data/version={v}")
    return gone


def current(spark: SparkSession, path: str) -> DataFrame:
    version = live(spark, path)
    if version is None:
        raise ValueError(f"nothing is published under {path}")
    return spark.read.parquet(f"{path}/data/version={version}").withColumn("snapshot_version", F.lit(version).cast("long"))


def latest(records: DataFrame, key: str = "path", version: str = "snapshot_version", tie: str = "size") -> DataFrame:
    """Of records of several versions in one table, the newest of each key; of equals the one largest in ``tie``."""
    w = Window.partitionBy(key).orderBy(F.desc(version), F.desc(tie))
    return records.withColumn("_n", F.row_number().over(w)).filter("_n = 1").drop("_n")


def diff(before: DataFrame, after: DataFrame, key: str = "path", values: tuple[str, ...] = VALUES) -> DataFrame:
    """path and change (create, update, delete) between two snapshots; one full outer join."""
    a = before.select(F.col(key).alias("_k"), F.struct(*values).alias("_a"))
    b = after.select(F.col(key).alias("_j"), F.struct(*values).alias("_b"))
    j = a.join(b, F.col("_k") == F.col("_j"), "full_outer")
    change = F.when(F.col("_k").isNull(), "create").when(F.col("_j").isNull(), "delete").when(~F.col("_a").eqNullSafe(F.col("_b")), "update")
    return j.select(F.coalesce("_k", "_j").alias(key), change.alias("change")).filter("change is not null")
