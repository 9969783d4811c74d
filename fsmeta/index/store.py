"""The primary index as a table: bootstrap from a snapshot, apply update and delete lists."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

COLUMNS = ("path", "source_id", "fid", "size", "last_seq")


def bootstrap(rows: DataFrame) -> DataFrame:
    """Index rows from a snapshot: path, source_id, fid, size at sequence 0."""
    return rows.select("path", "source_id", "fid", "size", F.lit(0).cast("long").alias("last_seq"))


def latest(actions: DataFrame) -> DataFrame:
    """Per path the action of the highest sequence, an update before a delete where equal. Doing it again changes nothing."""
    rank = F.when(F.col("action") == "delete", 0).otherwise(1)
    w = Window.partitionBy("source_id", "path").orderBy(F.desc("last_seq"), rank.desc())
    rows = actions.select("action", "path", "source_id", "fid", F.col("size").cast("long").alias("size"), "last_seq")
    return rows.withColumn("_n", F.row_number().over(w)).filter("_n = 1").drop("_n")


def apply(index: DataFrame, actions: DataFrame) -> DataFrame:
    """The index after the actions: per path the one of the highest sequence wins, deletes before
    updates where equal. Applying the same actions again changes nothing."""
    old = index.select(*COLUMNS, F.lit(1).alias("_rank"), F.lit("update").alias("action"))
    new = actions.select("path", "source_id", "fid", F.col("size").cast("long").alias("size"), "last_seq", F.when(F.col("action") == "delete", 2).otherwise(3).alias("_rank"), "action")
    w = Window.partitionBy("source_id", "path").orderBy(F.desc("last_seq"), F.desc("_rank"))
    best = old.unionByName(new).withColumn("_n", F.row_number().over(w)).filter("_n = 1")
    return best.filter("action <> 'delete'").select(*COLUMNS)


def freshness(actions: DataFrame, event_time: str = "ts", index_time: str = "applied") -> DataFrame:
    """Median and 99th percentile of the seconds from event to index."""
    lag = F.unix_timestamp(F.col(index_time).cast("timestamp")) - F.unix_timestamp(F.col(event_time).cast("timestamp"))
    return actions.agg(F.percentile(lag, F.lit(0.5)).alias("p50"), F.percentile(lag, F.lit(0.99)).alias("p99"))
