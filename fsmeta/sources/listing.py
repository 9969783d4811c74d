"""List source: a snapshot as tab-separated text of 18 columns, directories included."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

FILLER = ("inode", "generation", "snapshot", "kbytes", "pool", "replicas", "flags", "nlink")
SCHEMA = "path string, type string, mode int, uid long, gid long, size long, atime timestamp_ntz, ctime timestamp_ntz, mtime timestamp_ntz, fileset string, " + ", ".join(f"{c} string" for c in FILLER)


def read_listing(spark: SparkSession, path: str, schema: str = SCHEMA) -> DataFrame:
    """Explicit schema, so no pass to infer it; unused columns are not parsed."""
    return spark.read.schema(schema).option("sep", "\t").option("timestampNTZFormat", "yyyy-MM-dd'T'HH:mm:ss").csv(path)


def write_listing(df: DataFrame, path: str) -> None:
    rows = df.select(*[c for c in SCHEMA.replace(",", "").split()[0::2] if c in df.columns], *[F.lit("0").alias(c) for c in FILLER])
    rows.write.mode("overwrite").option("sep", "\t").option("timestampNTZFormat", "yyyy-MM-dd'T'HH:mm:ss").csv(path)
