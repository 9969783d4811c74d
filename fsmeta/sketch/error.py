"""Accuracy of quantile estimates against the exact distribution."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.sketch.exact import exact


def value_error(truth: DataFrame, estimate: DataFrame, keys: tuple[str, ...], qs: tuple[float, ...]) -> DataFrame:
    """keys..., quantile, value_error = |estimate - exact| / |exact|; where exact is 0: 0 if equal, else null."""
    j = truth.select(*keys, F.col("q").alias("t")).join(estimate.select(*keys, F.col("q").alias("e")), list(keys))
    rows = j.select(*keys, F.explode(F.array(*[F.struct(F.lit(q).alias("quantile"), F.get("t", i).alias("t"), F.get("e", i).alias("e")) for i, q in enumerate(qs)])).alias("x"))
    t, e = F.col("x.t"), F.col("x.e")
    return rows.select(*keys, "x.quantile", F.when(t == e, 0.0).when(t != 0, F.abs(e - t) / F.abs(t)).alias("value_error"))


def rank_error(df: DataFrame, estimate: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], qs: tuple[float, ...], tie: str = "closest") -> DataFrame:
    """keys..., quantile, rank_error = |place of the estimate in the sorted values - q n| / n.

    One pass: rows meet the estimates of all attributes of their group, and values are counted below and up
    to each. ``left`` takes the place before equal values, ``right`` the one after, ``closest`` the nearer.
    """
    keys = (*by, "attr")
    wide = estimate.groupBy(*by).agg(*[F.max(F.when(F.col("attr") == a, F.col("q"))).alias(f"_e{j}") for j, a in enumerate(attrs)])
    rows = df.select(*by, *[F.col(a).cast("double").alias(f"_v{j}") for j, a in enumerate(attrs)])
    rows = rows.join(wide, list(by)) if by else rows.crossJoin(F.broadcast(wide))
    below = [F.count_if(F.col(f"_v{j}") < F.get(f"_e{j}", i)).alias(f"l{j}_{i}") for j in range(len(attrs)) for i in range(len(qs))]
    upto = [F.count_if(F.col(f"_v{j}") <= F.get(f"_e{j}", i)).alias(f"r{j}_{i}") for j in range(len(attrs)) for i in range(len(qs))]
    there = [F.count(F.when(F.col(f"_e{j}").isNotNull(), F.col(f"_v{j}"))).alias(f"n{j}") for j in range(len(attrs))]
    counts = rows.groupBy(*by).agg(*there, *below, *upto)
    places = [F.struct(F.lit(a).alias("attr"), F.col(f"n{j}").alias("n"), *[F.col(f"{s}{j}_{i}").alias(f"{s}{i}") for i in range(len(qs)) for s in "lr"]) for j, a in enumerate(attrs)]
    counted = counts.select(*by, F.explode(F.array(*places)).alias("p")).select(*by, "p.*").filter("n > 0")

    def one(i: int, q: float):
        want, lo, hi = F.lit(q) * F.col("n"), F.col(f"l{i}"), F.col(f"r{i}")
        if tie == "left":
            off = F.abs(lo - want)
        elif tie == "right":
            off = F.abs(hi - want)
        else:
            off = F.greatest(F.lit(0.0), lo - want, want - hi)
        return F.struct(F.lit(q).alias("quantile"), (off / F.col("n")).alias("rank_error"))

    return counted.select(*keys, F.explode(F.array(*[one(i, q) for i, q in enumerate(qs)])).alias("x")).select(*keys, "x.quantile", "x.rank_error")


def summary(errors: DataFrame, column: str) -> DataFrame:
    """Least and greatest of the means of each quantile: how the comparison table reports an error."""
    means = errors.groupBy("quantile").agg(F.avg(column).alias("m"))
    return means.agg(F.min("m").alias(f"{column}_min"), F.max("m").alias(f"{column}_max"))


def errors(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], qs: tuple[float, ...], algo: str, min_files: int = 100, tie: str = "closest", **params) -> DataFrame:
    """algo, rank and value errors (min and max over quantiles) over groups with at least ``min_files`` rows."""
    from fsmeta.sketch.base import quantiles

    big = df.groupBy(*by).count().filter(F.col("count") >= min_files).select(*by)
    d = df.join(big, list(by), "left_semi")
    keys = (*by, "attr")
    est = quantiles(d, by, attrs, qs, algo, **params)
    v = summary(value_error(exact(d, by, attrs, qs), est, keys, qs), "value_error").withColumn("one", F.lit(1))
    r = summary(rank_error(d, est, by, attrs, qs, tie), "rank_error").withColumn("one", F.lit(1))
    return r.join(v, "one").select(F.lit(algo).alias("algo"), "rank_error_min", "rank_error_max", "value_error_min", "value_error_max")
