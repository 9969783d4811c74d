"""Exact quantiles: the reference that the summarizers are measured against."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def melt(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...]) -> DataFrame:
    """by..., attr, value: one row a value, without nulls."""
    return df.select(*by, F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).cast("double").alias("value")) for a in attrs])).alias("v")).select(*by, "v.attr", "v.value").filter("value is not null")


def exact(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], qs: tuple[float, ...]) -> DataFrame:
    """by..., attr, q (array): linear interpolation. Holds a value table per group in memory."""
    return melt(df, by, attrs).groupBy(*by, "attr").agg(F.percentile("value", F.array(*map(F.lit, qs))).alias("q"))


def exact_spilling(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], qs: tuple[float, ...]) -> DataFrame:
    """The same by a sort that can spill: rows are ranked and the two around each place interpolated."""
    w = Window.partitionBy(*by, "attr")
    ranked = melt(df, by, attrs).withColumn("i", F.row_number().over(w.orderBy("value")) - 1).withColumn("n", F.count("*").over(w))
    found = []
    for q in qs:
        at = (F.col("n") - 1) * q
        low = F.floor(at)
        part = at - low
        found.append(F.coalesce(F.sum(F.when(F.col("i") == low, F.col("value") * (1 - part))), F.lit(0.0)) + F.coalesce(F.sum(F.when((F.col("i") == low + 1) & (part > 0), F.col("value") * part)), F.lit(0.0)))
    return ranked.groupBy(*by, "attr").agg(F.array(*found).alias("q"))


def exact_selected(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], qs: tuple[float, ...], counts: DataFrame | None = None, alpha: float = 0.01) -> DataFrame:
    """The same without gathering a group anywhere: counts of logarithmic buckets tell in which buckets the wanted
    ranks lie, and only the values of those are counted and ranked, each bucket on its own.

    ``counts``: by..., attr, sign, bucket, n, where these are there already.
    """
    from fsmeta.sketch.dd import bucketed, buckets

    keys = (*by, "attr")
    place = (*keys, "sign", "bucket")
    counts = buckets(df, by, attrs, alpha) if counts is None else counts
    order = [F.col("sign"), F.col("sign") * F.col("bucket")]
    w = Window.partitionBy(*keys)
    run = counts.withColumn("upto", F.sum("n").over(w.orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))).withColumn("total", F.sum("n").over(w))
    at = [(F.col("total") - 1) * q for q in qs]
    ranks = [F.struct(F.lit(i).alias("i"), F.lit(high).alias("high"), (F.ceil(a) if high else F.floor(a)).alias("rank"), (a - F.floor(a)).alias("part")) for i, a in enumerate(at) for high in (False, True)]
    wanted = run.select(*place, (F.col("upto") - F.col("n")).alias("before"), "upto", F.explode(F.array(*ranks)).alias("w")).select(*place, "before", "upto", "w.*")
    wanted = wanted.filter((F.col("rank") >= F.col("before")) & (F.col("rank") < F.col("upto"))).drop("upto")
    # at most two buckets a quantile; the engine broadcasts them where they are few
    values = bucketed(df, by, attrs, alpha).join(wanted.select(*place).distinct(), list(place)).groupBy(*place, "value").agg(F.count("*").alias("n"))
    inside = Window.partitionBy(*place).orderBy("value").rowsBetween(Window.unboundedPreceding, 0)
    values = values.withColumn("hi", F.sum("n").over(inside)).withColumn("lo", F.col("hi") - F.col("n"))
    local = F.col("rank") - F.col("before")
    found = wanted.join(values.drop("n"), list(place)).filter((local >= F.col("lo")) & (local < F.col("hi")))
    share = F.when(F.col("high"), F.col("part")).otherwise(1 - F.col("part"))
    q = [F.sum(F.when(F.col("i") == i, F.col("value") * share)) for i in range(len(qs))]
    return found.groupBy(*keys).agg(F.array(*q).alias("q"))
