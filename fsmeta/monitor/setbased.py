"""The state manager as set operations: final places, resolved paths, update and delete lists.

A node table (source_id, fid, parent_fid, name, is_dir, size) is the hierarchy. Applying events gives
the table after them; paths resolve by walking up one level a round, directories only, all at once.
``update`` = objects touched or below a moved directory that exist after; ``delete`` = paths shown
before that are no longer valid for their object.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.monitor.reduce import STRUCTURAL
from fsmeta.plans import workspace


def apply_events(nodes: DataFrame, events: DataFrame) -> DataFrame:
    """The node table after the events, with last_seq of those touched."""
    place = F.when(F.col("op").isin(*STRUCTURAL), F.struct("parent_fid", "name"))
    last = events.groupBy("source_id", "fid").agg(
        F.max_by("op", "seq").alias("_op"),
        F.max("seq").alias("last_seq"),
        F.max_by("is_dir", "seq").alias("_dir"),
        F.max_by(place, F.when(place.isNotNull(), F.col("seq"))).alias("_place"),
        F.max_by("size", F.when(F.col("size").isNotNull(), F.col("seq"))).alias("_size"),
    )
    j = nodes.join(last, ["source_id", "fid"], "full_outer")
    moved = F.col("_place").isNotNull()
    after = j.select(
        "source_id",
        "fid",
        F.when(moved, F.col("_place.parent_fid")).otherwise(F.col("parent_fid")).alias("parent_fid"),
        F.when(moved, F.col("_place.name")).otherwise(F.col("name")).alias("name"),
        F.coalesce("is_dir", "_dir").alias("is_dir"),
        F.coalesce("_size", "size").alias("size"),
        "last_seq",
        F.coalesce(F.col("_op").isin("UNLINK", "RMDIR"), F.lit(False)).alias("_gone"),
    )
    return after.filter(~F.col("_gone") & F.col("name").isNotNull()).drop("_gone")


def resolve_paths(nodes: DataFrame, most_depth: int = 64) -> DataFrame:
    """Nodes with their path; null where an ancestor is missing. Directories climb by pointer
    doubling (a round joins what two rounds have reached), files join their directory once."""
    dirs = nodes.filter("is_dir").select("source_id", "fid", F.concat(F.lit("/"), "name").alias("tail"), F.col("parent_fid").alias("up"))
    now, rounds = dirs, 0
    while True:
        now = workspace.store(now, "climb")
        if now.filter("up is not null").isEmpty() or 1 << rounds > most_depth:
            break
        above = now.select("source_id", F.col("fid").alias("up"), F.col("tail").alias("_t"), F.col("up").alias("_u"), F.lit(1).alias("_found"))
        now = now.join(above, ["source_id", "up"], "left").select("source_id", "fid", F.when(F.col("up").isNull(), F.col("tail")).otherwise(F.concat("_t", "tail")).alias("tail"), F.when(F.col("_found") == 1, F.col("_u")).alias("up"))
        rounds += 1
    at = now.select("source_id", F.col("fid").alias("parent_fid"), F.col("tail").alias("_dir"))
    files = nodes.filter(~F.col("is_dir")).join(at, ["source_id", "parent_fid"], "left").withColumn("path", F.concat("_dir", F.lit("/"), "name")).drop("_dir")
    own = nodes.filter("is_dir").join(now.select("source_id", "fid", F.col("tail").alias("path")), ["source_id", "fid"])
    return own.select(*nodes.columns, "path").unionByName(files.select(*nodes.columns, "path"))


def actions(before: DataFrame, after: DataFrame) -> DataFrame:
    """action, source_id, fid, path, size, last_seq between two resolved node tables (files and links only)."""
    a = before.filter(~F.col("is_dir")).select("source_id", "fid", F.col("path").alias("old"))
    b = after.filter(~F.col("is_dir")).select("source_id", "fid", "path", "size", "last_seq")
    j = a.join(b, ["source_id", "fid"], "full_outer")
    gone = j.filter(F.col("old").isNotNull() & ~F.col("old").eqNullSafe(F.col("path")))
    kept = j.filter(F.col("path").isNotNull() & (F.col("last_seq").isNotNull() | ~F.col("old").eqNullSafe(F.col("path"))))
    seq = F.coalesce("last_seq", F.lit(0)).cast("long").alias("last_seq")
    return gone.select(F.lit("delete").alias("action"), "source_id", "fid", F.col("old").alias("path"), F.lit(None).cast("long").alias("size"), seq).unionByName(kept.select(F.lit("update").alias("action"), "source_id", "fid", "path", "size", seq))


def index_of(resolved: DataFrame) -> DataFrame:
    return resolved.filter(~F.col("is_dir") & F.col("path").isNotNull()).select("source_id", "fid", "path", "size")


def attach_stat(updates: DataFrame, stats: DataFrame | None = None, mode: str = "carried") -> DataFrame:
    """``call``: size from the stat relation (source_id, fid, size), one call each; ``carried``: as in the event."""
    if mode == "carried":
        return updates.withColumn("stat_calls", F.lit(0))
    s = stats.select("source_id", "fid", F.col("size").alias("_s"))
    return updates.join(s, ["source_id", "fid"], "left").withColumn("size", F.coalesce("_s", "size")).withColumn("stat_calls", F.when(F.col("action") == "update", 1).otherwise(0)).drop("_s")
