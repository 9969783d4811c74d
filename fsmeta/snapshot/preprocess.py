"""From raw snapshot rows to the reduced representation: fewer columns, no directories, escaped paths, chunks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fsmeta.functions.paths import escape_path

KEPT = ("path", "type", "mode", "uid", "gid", "size", "atime", "ctime", "mtime")


def reduce_columns(raw: DataFrame, spec: tuple[str, ...] = KEPT, extra: tuple[str, ...] = ()) -> DataFrame:
    """Only the columns that the indexes need; the choice reaches the scan."""
    return raw.select(*spec, *[c for c in extra if c in raw.columns])


def drop_directories(df: DataFrame) -> DataFrame:
    return df.filter(F.col("type").isin("f", "l"))


def preprocess(raw: DataFrame, extra: tuple[str, ...] = ("fileset",)) -> DataFrame:
    return drop_directories(reduce_columns(raw, extra=extra)).withColumn("path", escape_path(F.col("path")))


def write_chunks(df: DataFrame, path: str, target_rows: int = 1_000_000, align: str = "row", source: str = "source") -> None:
    """Headerless CSV chunks. ``row``: no file exceeds the target. ``source``: a chunk closes only
    after a whole source; sources are packed by their running row count."""
    if align == "row":
        df.write.option("maxRecordsPerFile", target_rows).option("escape", "\\").csv(path)
        return
    # running count over sources, by two levels: hash slices of sources, then sources in a slice
    counts = df.groupBy(source).count().withColumn("slice", F.pmod(F.xxhash64(source), F.lit(4096)))
    base = counts.groupBy("slice").agg(F.sum("count").alias("rows"))
    up = Window.orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    base = base.select("slice", F.coalesce(F.sum("rows").over(up), F.lit(0)).alias("base"))
    own = Window.partitionBy("slice").orderBy(source).rowsBetween(Window.unboundedPreceding, -1)
    chunk = counts.join(base, "slice").withColumn("chunk", F.floor((F.col("base") + F.coalesce(F.sum("count").over(own), F.lit(0))) / target_rows))
    rows = df.join(chunk.select(source, "chunk"), source).select(*df.columns, "chunk")
    rows.repartition("chunk").sortWithinPartitions("chunk", source).write.partitionBy("chunk").option("escape", "\\").csv(path)


def preprocess_stats(raw: DataFrame, reduced: DataFrame) -> DataFrame:
    """Rows, columns and text bytes before and after, and the share of bytes cut."""

    def size(df):
        return df.agg(F.count("*").alias("rows"), F.sum(sum((F.coalesce(F.octet_length(F.col(c).cast("string")), F.lit(0)) for c in df.columns), F.lit(len(df.columns)))).alias("bytes"))

    a = size(raw).select(F.col("rows").alias("rows_in"), F.col("bytes").alias("bytes_in"), F.lit(1).alias("one"))
    b = size(reduced).select(F.col("rows").alias("rows_out"), F.col("bytes").alias("bytes_out"), F.lit(1).alias("one"))
    j = a.join(F.broadcast(b), "one").drop("one")
    return j.select("*", F.lit(len(raw.columns)).alias("columns_in"), F.lit(len(reduced.columns)).alias("columns_out"), (1 - F.col("bytes_out") / F.col("bytes_in")).alias("cut"))
