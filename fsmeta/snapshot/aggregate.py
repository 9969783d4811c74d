"""Aggregate records: distribution summaries of size and times for users, groups and directories."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.fixtures import epoch
from fsmeta.functions.paths import prefix, prefixes
from fsmeta.sketch import dd as ddsketch
from fsmeta.sketch.exact import exact_selected

ATTRIBUTES = ("size", "atime", "ctime", "mtime")
QUANTILES = (0.10, 0.25, 0.50, 0.75, 0.90, 0.99)


def numbers(df: DataFrame, time_origin: float | None = None) -> DataFrame:
    """The four attributes as doubles; times as epoch seconds, or as ages before ``time_origin``."""
    times = {t: epoch(F.col(t)).cast("double") if time_origin is None else F.lit(time_origin) - epoch(F.col(t)) for t in ATTRIBUTES[1:]}
    return df.withColumns({"size": F.col("size").cast("double"), **times})


def principals(kinds: tuple[str, ...], dirs) -> list:
    """Array of (kind, id) for the principals of a row."""
    flat = [F.struct(F.lit(k).alias("kind"), c.cast("string").alias("id")) for k, c in (("user", F.col("uid")), ("group", F.col("gid"))) if k in kinds]
    all_ = F.array(*flat) if flat else F.array().cast("array<struct<kind:string,id:string>>")
    if "dir" in kinds:
        all_ = F.concat(all_, F.transform(dirs, lambda d: F.struct(F.lit("dir").alias("kind"), d.alias("id"))))
    return all_


def expand(df: DataFrame, low: int, high: int, kinds: tuple[str, ...] = ("user", "group", "dir"), dir_filter: str | None = None) -> DataFrame:
    """A row for each principal of each row: the costly way, kept for comparison."""
    dirs = prefixes(F.col("path"), low, high)
    if dir_filter:
        dirs = F.filter(dirs, lambda d: d.startswith(dir_filter))
    return df.select(F.explode(principals(kinds, dirs)).alias("p"), *ATTRIBUTES).select("p.kind", "p.id", *ATTRIBUTES)


def leaf_keys(df: DataFrame, high: int) -> DataFrame:
    return df.withColumn("leaf", prefix(F.col("path"), high))


def roll_up(partial: DataFrame, low: int, high: int, kinds: tuple[str, ...], sums: dict, dir_filter: str | None = None, keys: tuple[str, ...] = ()) -> DataFrame:
    """Summaries of (uid, gid, leaf directory) spread over the principals and added up there."""
    dirs = prefixes(F.concat(F.when(F.col("leaf") == "/", F.lit("")).otherwise(F.col("leaf")), F.lit("/x")), low, high)
    if dir_filter:
        dirs = F.filter(dirs, lambda d: d.startswith(dir_filter))
    rest = [c for c in partial.columns if c not in ("uid", "gid", "leaf")]
    spread = partial.select(F.explode(principals(kinds, dirs)).alias("p"), *rest).select("p.kind", "p.id", *rest)
    return spread.groupBy("kind", "id", *keys).agg(*[f(c).alias(c) for c, f in sums.items()])


def totals(df: DataFrame, low: int, high: int, kinds: tuple[str, ...] = ("user", "group", "dir"), dir_filter: str | None = None) -> DataFrame:
    """kind, id, file_count, and min, max, sum of each attribute; summed before it is spread."""
    d = leaf_keys(numbers(df), high)
    aggs = [F.count("*").alias("file_count")]
    sums = {"file_count": F.sum}
    for a in ATTRIBUTES:
        for name, f in (("min", F.min), ("max", F.max), ("sum", F.sum)):
            aggs.append(f(a).alias(f"{a}_{name}"))
            sums[f"{a}_{name}"] = f
    return roll_up(d.groupBy("uid", "gid", "leaf").agg(*aggs), low, high, kinds, sums, dir_filter)


def dd_buckets(df: DataFrame, low: int, high: int, kinds: tuple[str, ...] = ("user", "group", "dir"), alpha: float = 0.01, after: bool = True, dir_filter: str | None = None, time_origin: float | None = None) -> DataFrame:
    """kind, id, attr, sign, bucket, n. ``after``: counted per leaf before it is spread, else each row is spread."""
    d = numbers(df, time_origin)
    if after:
        part = ddsketch.buckets(leaf_keys(d, high), ("uid", "gid", "leaf"), ATTRIBUTES, alpha)
        return roll_up(part, low, high, kinds, {"n": F.sum}, dir_filter, ("attr", "sign", "bucket"))
    return ddsketch.buckets(expand(d, low, high, kinds, dir_filter), ("kind", "id"), ATTRIBUTES, alpha)


def plain_id():
    """A principal of the counting table as the aggregate side names it."""
    return F.when(F.col("kind") == "dir", F.col("id")).otherwise(F.substring("id", 2, 100))


def complete_principals(seen: DataFrame, counts: DataFrame) -> DataFrame:
    """Principals with the counting table's number of objects, and whether all have arrived (``complete``)."""
    named = counts.select("kind", plain_id().alias("id"), F.col("n").alias("expected"))
    return named.join(seen, ["kind", "id"], "left").withColumn("complete", F.coalesce(F.col("file_count") == F.col("expected"), F.lit(False)))


def complete_by_shard(arrived: DataFrame, counts: DataFrame) -> DataFrame:
    """kind, id, shards, missing (shards whose objects have not all arrived), complete. Both tables:
    kind, id, shard_id, n; ``counts`` from the counting stage, ``arrived`` from what is summed up here."""
    a = arrived.select("kind", "id", "shard_id", F.col("n").alias("_have"))
    j = counts.join(a, ["kind", "id", "shard_id"], "left")
    missing = F.count_if(F.coalesce(F.col("_have") != F.col("n"), F.lit(True)))
    out = j.groupBy("kind", "id").agg(F.count("*").alias("shards"), missing.alias("missing"))
    return out.select("kind", plain_id().alias("id"), "shards", "missing", (F.col("missing") == 0).alias("complete"))


def aggregate(df: DataFrame, low: int = 1, high: int = 5, kinds: tuple[str, ...] = ("user", "group", "dir"), qs: tuple[float, ...] = QUANTILES, sketch: str = "dd", alpha: float = 0.01, dir_filter: str | None = None, after: bool = True) -> DataFrame:
    """kind, id, file_count and <attr>_min, _max, _mean, _sum, _pNN for each attribute."""
    base = totals(df, low, high, kinds, dir_filter)
    if sketch == "dd":
        q = ddsketch.quantiles(dd_buckets(df, low, high, kinds, alpha, after, dir_filter), ("kind", "id", "attr"), qs, alpha)
    elif sketch == "exact":
        counts = dd_buckets(df, low, high, kinds, alpha, after, dir_filter)
        q = exact_selected(expand(numbers(df), low, high, kinds, dir_filter), ("kind", "id"), ATTRIBUTES, qs, counts, alpha)
    else:
        from fsmeta.sketch.base import quantiles

        q = quantiles(expand(numbers(df), low, high, kinds, dir_filter), ("kind", "id"), ATTRIBUTES, qs, sketch)
    return with_quantiles(base, q, qs)


def with_quantiles(base: DataFrame, q: DataFrame, qs: tuple[float, ...]) -> DataFrame:
    """Totals with means and, from kind, id, attr, q, one column a quantile, clamped by the exact ends."""
    base = base.withColumns({f"{a}_mean": F.col(f"{a}_sum") / F.col("file_count") for a in ATTRIBUTES})
    names = [(i, name_of(x)) for i, x in enumerate(qs)]
    wide = q.groupBy("kind", "id").agg(*[F.max(F.when(F.col("attr") == a, F.get("q", i))).alias(f"{a}_{n}") for a in ATTRIBUTES for i, n in names])
    j = base.join(wide, ["kind", "id"])
    clamp = {f"{a}_{n}": F.least(F.greatest(f"{a}_{n}", f"{a}_min"), f"{a}_max") for a in ATTRIBUTES for _, n in names}
    return j.withColumns(clamp)


def name_of(q: float) -> str:
    return "p" + f"{q * 100:.10g}".replace(".", "_")


def to_documents(agg: DataFrame, qs: tuple[float, ...] = QUANTILES, admins: tuple[str, ...] = ("group:admins",)) -> DataFrame:
    """subject, visible_to and content of aggregate records; sent at once, as they are few."""
    subject = F.concat("kind", F.lit(":"), "id")
    fields = ["min", *map(name_of, qs), "max", "mean"]
    content = F.struct("file_count", *[F.struct(*[F.col(f"{a}_{f}").alias(f) for f in fields], *([F.col("size_sum").alias("total")] if a == "size" else [])).alias(a) for a in ATTRIBUTES])
    return agg.select(subject.alias("subject"), F.array(F.when(F.col("kind") == "dir", F.lit("public")).otherwise(subject), *map(F.lit, admins)).alias("visible_to"), content.alias("content"))
