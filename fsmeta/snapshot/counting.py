"""Counting: shard ids, counts per principal and shard, recursive directory totals, merged counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fsmeta.functions.paths import prefix

ROW = ("path", "type", "mode", "uid", "gid", "size", "atime", "ctime", "mtime")


def shard_id(num_shards: int, cols: tuple[str, ...] = ROW) -> Column:
    """CRC-32 of the row as comma-separated UTF-8, modulo the number of shards."""
    row = F.concat_ws(",", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in cols])
    return (F.crc32(row.cast("binary")) % num_shards).cast("int")


def shard_counts(df: DataFrame, directory_max: int, num_shards: int = 64, kinds: tuple[str, ...] = ("user", "group", "dir")) -> DataFrame:
    """kind, id, shard_id, n; directories are cut to ``directory_max`` levels and counted without descendants.

    One scan and one shuffle: rows are counted by (uid, gid, directory, shard) before they
    are spread over the three kinds.
    """
    base = df.select("uid", "gid", prefix(F.col("path"), directory_max).alias("dir"), shard_id(num_shards).alias("shard_id")).groupBy("uid", "gid", "dir", "shard_id").agg(F.count("*").alias("n"))
    each = {"user": F.concat(F.lit("u"), "uid"), "group": F.concat(F.lit("g"), "gid"), "dir": F.col("dir")}
    spread = base.select(F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), each[k].alias("id")) for k in kinds])).alias("p"), "shard_id", "n")
    return spread.groupBy(F.col("p.kind").alias("kind"), F.col("p.id").alias("id"), "shard_id").agg(F.sum("n").alias("n"))


def recursive_counts(counts: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """id, n: totals of every directory with all its descendants, from the counts without (by ``keep``)."""
    own = counts.filter("kind = 'dir'").groupBy("id", *keep).agg(F.sum("n").alias("n"))
    names = F.filter(F.split("id", "/"), lambda x: x != "")
    above = F.transform(F.sequence(F.lit(0), F.size(names)), lambda i: F.concat(F.lit("/"), F.array_join(F.slice(names, 1, i), "/")))
    return own.select(F.explode(above).alias("id"), *keep, "n").groupBy("id", *keep).agg(F.sum("n").alias("n"))


def merge_counts(counts: DataFrame, low: int = 1, by_shard: bool = False) -> DataFrame:
    """kind, id, n: one row a principal, shards added up (or a row a shard); directories with descendants, from level ``low``."""
    keep = ("shard_id",) if by_shard else ()
    flat = counts.filter("kind <> 'dir'").groupBy("kind", "id", *keep).agg(F.sum("n").alias("n"))
    dirs = recursive_counts(counts, keep).filter(F.size(F.filter(F.split("id", "/"), lambda x: x != "")) >= low)
    return flat.unionByName(dirs.select(F.lit("dir").alias("kind"), "id", *keep, "n"))
