"""Questions to the two indexes: object filters, and the administrative catalogue."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fsmeta.fixtures import epoch


@dataclass(frozen=True)
class Match:
    """One predicate of the query builder. op: eq, ne, lt, le, gt, ge, between, in, like, regex, prefix, null, bit."""

    field: str
    op: str
    value: object = None

    def column(self) -> Column:
        c, v = F.col(self.field), self.value
        build = {
            "eq": lambda: c.eqNullSafe(F.lit(v)), "ne": lambda: ~c.eqNullSafe(F.lit(v)), "lt": lambda: c < v, "le": lambda: c <= v, "gt": lambda: c > v, "ge": lambda: c >= v,
            "between": lambda: c.between(*v), "in": lambda: c.isin(*v), "like": lambda: c.like(v), "regex": lambda: c.cast("string").rlike(v), "prefix": lambda: c.startswith(v),
            "null": lambda: c.isNull() if v is not False else c.isNotNull(), "bit": lambda: c.bitwiseAND(F.lit(v)) == v,
        }
        if self.op not in build:
            raise ValueError(f"unknown op {self.op}")
        return build[self.op]()


def search(primary: DataFrame, filters: list[Match], as_user: tuple[str, ...] | None = None) -> DataFrame:
    """Objects that fulfil all filters, and that the principals may see if given."""
    for f in filters:
        primary = primary.filter(f.column())
    return primary if as_user is None else visible(primary, as_user)


def visible(primary: DataFrame, who: tuple[str, ...], admins: tuple[str, ...] = ("group:admins",)) -> DataFrame:
    """Rows that one of the principals may see; admins see all."""
    if set(who) & set(admins):
        return primary
    seen = F.array(F.concat(F.lit("user:"), "uid"), F.concat(F.lit("group:"), "gid"))
    return primary.filter(F.arrays_overlap(seen, F.array(*map(F.lit, who))))


AGGREGATE_FIELDS = frozenset(("kind", "id", "file_count"))


def route(filters: list[Match]) -> str:
    """'aggregate' if the summaries alone can answer, else 'primary'."""
    return "aggregate" if all(f.field in AGGREGATE_FIELDS or f.field.startswith(("size_", "atime_", "ctime_", "mtime_")) for f in filters) else "primary"


def by_name(p: DataFrame, pattern: str) -> DataFrame:
    return p.filter(F.col("path").like(pattern)).select("path", "size")


def world_writable(p: DataFrame) -> DataFrame:
    return p.filter((F.col("mode") % 10).cast("int").bitwiseAND(F.lit(2)) > 0).select("path", "mode")


def untouched(p: DataFrame, as_of: str, months: int) -> DataFrame:
    return p.filter(F.col("atime") < F.lit(as_of).cast("timestamp_ntz") - F.make_ym_interval(F.lit(0), F.lit(months))).select("path", "atime")


def big_cold(p: DataFrame, size: int, as_of: str, months: int = 6) -> DataFrame:
    return p.filter((F.col("size") > size) & (F.col("atime") < F.lit(as_of).cast("timestamp_ntz") - F.make_ym_interval(F.lit(0), F.lit(months)))).select("path", "size")


def replicas(p: DataFrame) -> DataFrame:
    return p.groupBy("checksum").agg(F.count("*").alias("copies"), F.sum("size").alias("bytes")).filter("copies > 1 and checksum is not null")


def over_limit(dirs: DataFrame, limit: int) -> DataFrame:
    """Directories (id, n) whose recursive count is over a limit."""
    return dirs.filter(F.col("n") > limit)


def per_project(p: DataFrame) -> DataFrame:
    return p.groupBy("project").agg(F.count("*").alias("files"), F.sum("size").alias("bytes"))


def near_quota(p: DataFrame, quota: DataFrame, ratio: float = 0.9) -> DataFrame:
    used = p.groupBy("project").agg(F.sum("size").alias("used"))
    return used.join(quota, "project").withColumn("ratio", F.round(F.col("used") / F.col("quota"), 6)).filter(F.col("ratio") > ratio)


def orphans(p: DataFrame, active: DataFrame) -> DataFrame:
    return p.join(active, "uid", "left_anti").select("path", "uid")


def past_retention(p: DataFrame, before: str) -> DataFrame:
    return p.filter(F.col("mtime") < F.lit(before).cast("timestamp_ntz")).select("path", "mtime")


def small_files(p: DataFrame, limit: int = 1 << 20, k: int = 10) -> DataFrame:
    return p.filter(F.col("size") < limit).groupBy("uid").agg(F.count("*").alias("small_files")).orderBy(F.desc("small_files"), "uid").limit(k)


def per_user(p: DataFrame) -> DataFrame:
    return p.groupBy("uid").agg(F.count("*").alias("files"), F.sum("size").alias("bytes"))


def directory_sizes(p: DataFrame, by: str) -> DataFrame:
    parent = F.substring_index("path", "/", -1)
    return p.groupBy(by, F.col("path").substr(F.lit(1), F.length("path") - F.length(parent) - 1).alias("dir")).agg(F.sum("size").alias("bytes"))


def p99_directory(p: DataFrame, by: str) -> DataFrame:
    return directory_sizes(p, by).groupBy(by).agg(F.count("*").alias("dirs"), F.round(F.percentile("bytes", 0.99), 3).alias("p99"))


def small_last_week(p: DataFrame, as_of: str, limit: int = 1 << 20) -> DataFrame:
    end = F.lit(as_of).cast("timestamp_ntz")
    return p.filter((F.col("ctime") >= end - F.make_dt_interval(F.lit(7))) & (F.col("ctime") < end) & (F.col("size") < limit)).groupBy("uid").agg(F.count("*").alias("small_files"))


def top_users(agg: DataFrame, k: int = 10) -> DataFrame:
    """From the aggregate index: user records by total size."""
    return agg.filter("kind = 'user'").select(F.col("id").cast("long").alias("uid"), F.col("size_sum").cast("long").alias("bytes")).orderBy(F.desc("bytes"), "uid").limit(k)


def summary(agg: DataFrame, uid: int) -> DataFrame:
    """Template text of one user's aggregate record."""
    return agg.filter((F.col("kind") == "user") & (F.col("id") == str(uid))).select("id", F.format_string("User %s owns %d files, %d bytes in total, the largest of %d bytes.", "id", "file_count", F.col("size_sum").cast("long"), F.col("size_max").cast("long")).alias("summary"))


def owned_in(p: DataFrame, uid: int, directory: str) -> DataFrame:
    return p.filter((F.col("uid") == uid) & F.col("path").startswith(directory.rstrip("/") + "/")).select("path", "size")


def size_age(p: DataFrame, as_of: str) -> DataFrame:
    """Correlation of size and age in days, per group."""
    age = (F.unix_timestamp(F.lit(as_of).cast("timestamp")) - epoch(F.col("mtime"))) / 86400
    return p.groupBy("gid").agg(F.round(F.corr(F.col("size").cast("double"), age), 6).alias("corr"))
