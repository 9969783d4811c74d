"""Relative-error sketch with logarithmic buckets, kept as a relation of counts.

Bucket of x > 0: ceil(log_gamma x), gamma = (1 + a) / (1 - a); its representative value
2 gamma^i / (gamma + 1) is within a of every x in it. Negative values have a mirrored store,
zeros a bucket of their own. Merging is adding counts, so no order of merging changes anything.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fsmeta.sketch.exact import melt


def gamma(alpha: float) -> float:
    return (1 + alpha) / (1 - alpha)


def bucketed(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], alpha: float = 0.01) -> DataFrame:
    """by..., attr, value, sign, bucket: one row a value."""
    v = F.col("value")
    return melt(df, by, attrs).select(*by, "attr", "value", F.signum(v).cast("int").alias("sign"), F.when(v == 0, 0).otherwise(F.ceil(F.log(F.abs(v)) / F.lit(math.log(gamma(alpha))))).cast("long").alias("bucket"))


def buckets(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], alpha: float = 0.01) -> DataFrame:
    return bucketed(df, by, attrs, alpha).groupBy(*by, "attr", "sign", "bucket").agg(F.count("*").alias("n"))


def merge(parts: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    return parts.groupBy(*keys, "sign", "bucket").agg(F.sum("n").alias("n"))


def collapse(b: DataFrame, keys: tuple[str, ...], bins: int = 2048) -> DataFrame:
    """At most ``bins`` buckets a key: the lowest ones fall into the lowest that stays."""
    w = Window.partitionBy(*keys).orderBy(F.desc(F.col("sign") * (F.col("bucket") + F.lit(1 << 40))))
    ranked = b.withColumn("_r", F.row_number().over(w))
    low = F.max(F.when(F.col("_r") == bins, F.struct("sign", "bucket"))).over(Window.partitionBy(*keys))
    ranked = ranked.withColumn("_low", low).withColumn("_to", F.when(F.col("_r") > bins, F.col("_low")).otherwise(F.struct("sign", "bucket")))
    return ranked.groupBy(*keys, F.col("_to.sign").alias("sign"), F.col("_to.bucket").alias("bucket")).agg(F.sum("n").alias("n"))


def value(alpha: float):
    g = gamma(alpha)
    return F.when(F.col("sign") == 0, F.lit(0.0)).otherwise(F.col("sign") * 2 * F.pow(F.lit(g), F.col("bucket").cast("double")) / (g + 1))


def quantiles(b: DataFrame, keys: tuple[str, ...], qs: tuple[float, ...], alpha: float = 0.01) -> DataFrame:
    """keys..., q (array): value of the first bucket whose running count exceeds q (n - 1).

    Buckets are few, so the window sorts summaries, never values.
    """
    order = [F.col("sign"), F.col("sign") * F.col("bucket")]
    w = Window.partitionBy(*keys)
    run = b.withColumn("upto", F.sum("n").over(w.orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))).withColumn("total", F.sum("n").over(w))
    found = [F.min_by(value(alpha), F.when(F.col("upto") > F.lit(q) * (F.col("total") - 1), F.col("upto"))) for q in qs]
    return run.groupBy(*keys).agg(F.array(*found).alias("q"))
