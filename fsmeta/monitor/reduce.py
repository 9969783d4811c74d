"""Reduction rules on batches: coalescing, cancellation of files and directories, rename override.

A batch with a directory rename passes as it is (``override='batch'``), or is cut into stretches
around each such rename that are reduced on their own (``'barrier'``).
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Protocol

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

STRUCTURAL = ("CREATE", "MKDIR", "RENAME")
OUT = ("source_id", "batch_id", "seq", "ts", "op", "fid", "is_dir", "parent_fid", "name", "size")


class ReductionRule(Protocol):
    def drops(self) -> Column:
        """Over a coalesced group (first_op, last_op, is_dir): whether it vanishes."""


@dataclass(frozen=True)
class CancelPair:
    begin: str
    end: str

    def drops(self) -> Column:
        return (F.col("first_op") == self.begin) & (F.col("last_op") == self.end)


CANCEL_FILE, CANCEL_DIR = CancelPair("CREATE", "UNLINK"), CancelPair("MKDIR", "RMDIR")
RULES: tuple[ReductionRule, ...] = (CANCEL_FILE, CANCEL_DIR)


def dir_rename() -> Column:
    return (F.col("op") == "RENAME") & F.col("is_dir")


def coalesced(batched: DataFrame, extra: tuple[str, ...] = ()) -> DataFrame:
    """One row for each (source, batch, id): first and last operation, last place and last size."""
    structural = F.when(F.col("op").isin(*STRUCTURAL), F.struct("parent_fid", "name"))
    return batched.groupBy("source_id", "batch_id", *extra, "fid").agg(
        F.max("seq").alias("seq"),
        F.max_by("ts", "seq").alias("ts"),
        F.count("*").alias("events"),
        F.min_by("op", "seq").alias("first_op"),
        F.max_by("op", "seq").alias("last_op"),
        F.max(F.when(F.col("op") == "RENAME", 1).otherwise(0)).alias("renamed"),
        F.max(F.when(dir_rename(), 1).otherwise(0)).alias("dir_renamed"),
        F.max_by("is_dir", "seq").alias("is_dir"),
        F.max_by(structural, F.when(structural.isNotNull(), F.col("seq"))).alias("place"),
        F.max_by("size", F.when(F.col("size").isNotNull(), F.col("seq"))).alias("size"),
    )


def survivor(groups: DataFrame) -> DataFrame:
    """Each group as one event: removal, creation, rename or plain update."""
    op = F.when(F.col("last_op").isin("UNLINK", "RMDIR"), F.col("last_op")).when(F.col("first_op").isin("CREATE", "MKDIR"), F.col("first_op")).when(F.col("renamed") == 1, "RENAME").otherwise("SETATTR")
    return groups.withColumn("op", op).withColumn("parent_fid", F.col("place.parent_fid")).withColumn("name", F.col("place.name")).select(*OUT)


def reduce(batched: DataFrame, rules: tuple[ReductionRule, ...] = RULES, override: str = "batch") -> DataFrame:
    """Surviving events of batches (source_id, batch_id, seq, ...)."""
    w = Window.partitionBy("source_id", "batch_id")
    if override == "batch":
        e = batched.withColumn("_raw", F.max(dir_rename().cast("int")).over(w) == 1).withColumn("_part", F.lit(0))
    elif override == "barrier":
        e = batched.withColumn("_raw", dir_rename())
        e = e.withColumn("_part", F.sum(F.col("_raw").cast("int")).over(w.orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)))
    else:
        raise ValueError(f"unknown override {override}")
    groups = coalesced(e.filter(~F.col("_raw")), ("_part",))
    for rule in rules:
        groups = groups.filter(~rule.drops())
    return survivor(groups).unionByName(e.filter("_raw").select(*OUT))


def reduce_stats(batched: DataFrame, reduced: DataFrame, opens: DataFrame | None = None) -> DataFrame:
    """Per source: events in, opens dropped before, groups cancelled by kind, coalesced away, events out."""
    w = Window.partitionBy("source_id", "batch_id")
    plain = batched.withColumn("_raw", F.max(dir_rename().cast("int")).over(w)).filter("_raw = 0")
    g = coalesced(plain)
    file_, dir_ = CANCEL_FILE.drops(), CANCEL_DIR.drops()
    stats = g.groupBy("source_id").agg(
        F.count_if(file_).alias("cancelled_files"),
        F.count_if(dir_).alias("cancelled_dirs"),
        F.coalesce(F.sum(F.when(~(file_ | dir_), F.col("events") - 1)), F.lit(0)).alias("coalesced"),
        F.coalesce(F.sum(F.when(file_ | dir_, F.col("events"))), F.lit(0)).alias("cancelled_events"),
    )
    out = batched.groupBy("source_id").agg(F.count("*").alias("events_in")).join(reduced.groupBy("source_id").agg(F.count("*").alias("events_out")), "source_id", "left").join(stats, "source_id", "left")
    if opens is not None:
        out = out.join(opens.filter("op = 'OPEN'").groupBy("source_id").agg(F.count("*").alias("opens_dropped")), "source_id", "left")
    return out.na.fill(0)


def batch_stats(batched: DataFrame) -> DataFrame:
    """What ``reduce_stats`` says of ``reduce`` with its standard rules, and the number of batches, from one pass over
    the groups of each batch: a batch with a directory rename passes, so its groups count as events only."""
    file_, dir_ = CANCEL_FILE.drops(), CANCEL_DIR.drops()
    batches = coalesced(batched).groupBy("source_id", "batch_id").agg(
        F.max("dir_renamed").alias("raw"),
        F.sum("events").alias("events_in"),
        F.count_if(~(file_ | dir_)).alias("left"),
        F.count_if(file_).alias("cancelled_files"),
        F.count_if(dir_).alias("cancelled_dirs"),
        F.coalesce(F.sum(F.when(file_ | dir_, F.col("events"))), F.lit(0)).alias("cancelled_events"),
    )
    plain = F.col("raw") == 0
    counts = {c: F.when(plain, F.col(c)).otherwise(0) for c in ("cancelled_files", "cancelled_dirs", "cancelled_events")}
    counts |= {"events_in": F.col("events_in"), "events_out": F.when(plain, F.col("left")).otherwise(F.col("events_in")), "coalesced": F.when(plain, F.col("events_in") - F.col("cancelled_events") - F.col("left")).otherwise(0)}
    return batches.groupBy("source_id").agg(F.count("*").alias("batches"), *[F.sum(v).alias(k) for k, v in counts.items()])
