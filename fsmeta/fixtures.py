"""File-system views on the given tables, as DataFrames and as DuckDB SQL.

Each view exists twice: ``fs_large(spark, dir)`` and ``SQL["fs_large"]``. Both give the same rows;
all expressions are deterministic. Times are TimestampNTZ, as the tables have them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

REDUCED = ("path", "type", "mode", "uid", "gid", "size", "atime", "ctime", "mtime", "fileset", "checksum", "project")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def days(column, n):
    return column + F.make_dt_interval(n.cast("int") if hasattr(n, "cast") else F.lit(n))


def epoch(column):
    """Seconds since 1970 of a time without zone, read as UTC."""
    return F.unix_timestamp(column.cast("timestamp"))


def fs_large(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem")
    s, n, p = (table(spark, sf_dir, t) for t in ("supplier", "nation", "part"))
    j = li.join(s, li.l_suppkey == s.s_suppkey).join(n, s.s_nationkey == n.n_nationkey).join(p, li.l_partkey == p.p_partkey)
    path = F.concat(F.lit("/fs/r"), "n_regionkey", F.lit("/n"), "n_nationkey", F.lit("/u"), "l_suppkey", F.lit("/"), "p_type", F.lit("/"), "p_brand", F.lit("/o"), "l_orderkey", F.lit("_"), "l_linenumber", F.lit("_"), "l_partkey", F.lit(".dat"))
    mode = F.when((F.col("l_returnflag") == "R") & (F.col("l_linestatus") == "F"), 100777).when(F.col("l_returnflag") == "R", 100600).when(F.col("l_returnflag") == "A", 100644).otherwise(100664)
    ctime = days(F.col("l_shipdate"), F.col("l_linenumber"))
    return j.select(
        path.alias("path"),
        F.when(F.col("l_linenumber") == 7, "l").otherwise("f").alias("type"),
        mode.alias("mode"),
        F.col("l_suppkey").cast("long").alias("uid"),
        F.col("s_nationkey").cast("long").alias("gid"),
        F.round(F.col("l_extendedprice") * 100).cast("long").alias("size"),
        days(ctime, F.col("l_quantity")).alias("atime"),
        ctime.alias("ctime"),
        F.col("l_shipdate").alias("mtime"),
        F.col("l_linestatus").alias("fileset"),
        F.lit(None).cast("string").alias("checksum"),
        F.col("p_brand").alias("project"),
    )


def fs_medium_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Files of ``orders`` and one directory row for each distinct parent, as a listing has them."""
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    j = o.join(c, o.o_custkey == c.c_custkey)
    parent = F.concat(F.lit("/proj/"), "c_mktsegment", F.lit("/n"), "c_nationkey", F.lit("/u"), "o_custkey")
    mode = F.when(F.col("o_orderstatus") == "O", 100664).when(F.col("o_orderstatus") == "F", 100600).otherwise(100777)
    files = j.select(
        F.concat(parent, F.lit("/o"), "o_orderkey", F.lit(".bin")).alias("path"),
        F.lit("f").alias("type"),
        mode.alias("mode"),
        F.col("o_custkey").cast("long").alias("uid"),
        F.col("c_nationkey").cast("long").alias("gid"),
        F.round(F.col("o_totalprice") * 100).cast("long").alias("size"),
        days(F.col("o_orderdate"), F.col("o_orderkey") % 90).alias("atime"),
        days(F.col("o_orderdate"), F.col("o_orderkey") % 7).alias("ctime"),
        F.col("o_orderdate").alias("mtime"),
        F.col("c_mktsegment").alias("fileset"),
        F.lit(None).cast("string").alias("checksum"),
        F.lit(None).cast("string").alias("project"),
    )
    dirs = j.groupBy(parent.alias("path"), F.col("o_custkey").cast("long").alias("uid"), F.col("c_nationkey").cast("long").alias("gid"), F.col("c_mktsegment").alias("fileset")).agg(F.max("o_orderdate").alias("mtime"))
    dirs = dirs.select("path", F.lit("d").alias("type"), F.lit(40755).alias("mode"), "uid", "gid", F.lit(4096).cast("long").alias("size"), F.col("mtime").alias("atime"), F.col("mtime").alias("ctime"), "mtime", "fileset", F.lit(None).cast("string").alias("checksum"), F.lit(None).cast("string").alias("project"))
    return files.unionByName(dirs)


def fs_medium(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fs_medium_raw(spark, sf_dir).filter(F.col("type").isin("f", "l"))


def fs_small(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lab = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels").select("doc_id", "quality")
    d = d.join(lab, "doc_id", "left")
    base = days(F.lit("2024-01-01").cast("timestamp_ntz"), F.lit(0)) + F.make_dt_interval(F.lit(0), F.col("doc_id").cast("int"))
    return d.select(
        F.concat(F.lit("/home/"), "source", F.lit("/"), "lang", F.lit("/d"), "doc_id", F.lit(".txt")).alias("path"),
        F.lit("f").alias("type"),
        F.when(F.col("doc_id") % 10 == 0, 100777).otherwise(100644).alias("mode"),
        F.regexp_extract("source", "(\\d+)", 1).cast("long").alias("uid"),
        F.when(F.col("lang") == "de", 1).when(F.col("lang") == "en", 2).when(F.col("lang") == "es", 3).when(F.col("lang") == "fr", 4).otherwise(0).cast("long").alias("gid"),
        F.octet_length("text").cast("long").alias("size"),
        days(base, F.col("n_chars") % 60).alias("atime"),
        days(base, 1).alias("ctime"),
        base.alias("mtime"),
        F.lit(None).cast("string").alias("fileset"),
        F.md5("text").alias("checksum"),
        F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "poor").otherwise("unlabelled").alias("project"),
    )


def fs_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "pages")
    t = F.lit("2024-01-01").cast("timestamp_ntz") + F.make_dt_interval(F.lit(0), F.col("page_id").cast("int"))
    return p.select(
        F.concat(F.lit("/"), F.regexp_replace("url", "^[a-z]+://", "")).alias("path"), F.lit("f").alias("type"), F.lit(100644).alias("mode"),
        (F.col("page_id") % 10).alias("uid"), F.lit(0).cast("long").alias("gid"), F.octet_length("html").cast("long").alias("size"),
        t.alias("atime"), t.alias("ctime"), t.alias("mtime"), F.lit(None).cast("string").alias("fileset"), F.lit(None).cast("string").alias("checksum"), F.lit(None).cast("string").alias("project"),
    )


def fs_chats(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    t = F.lit("2024-01-01").cast("timestamp_ntz") + F.make_dt_interval(F.lit(0), F.lit(0), F.col("turn").cast("int"))
    return c.select(
        F.concat(F.lit("/chat/c"), "conv_id", F.lit("/t"), "turn", F.lit(".txt")).alias("path"), F.lit("f").alias("type"), F.lit(100644).alias("mode"),
        (F.col("conv_id") % 10).alias("uid"), F.when(F.col("role") == "user", 1).when(F.col("role") == "assistant", 2).otherwise(3).cast("long").alias("gid"), F.octet_length("text").cast("long").alias("size"),
        t.alias("atime"), t.alias("ctime"), t.alias("mtime"), F.lit(None).cast("string").alias("fileset"), F.lit(None).cast("string").alias("checksum"), F.col("role").alias("project"),
    )


def versions(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Two snapshots of fs_large: before 2000, and all with planted deletions and size changes."""
    v = fs_large(spark, sf_dir).withColumn("okey", F.regexp_extract("path", "/o(\\d+)_", 1).cast("long"))
    v1 = v.filter(F.col("mtime") < F.lit("2000-01-01").cast("timestamp_ntz")).drop("okey")
    v2 = v.filter(F.col("okey") % 97 != 0).withColumn("size", F.col("size") + F.when(F.col("okey") % 89 == 0, 1).otherwise(0)).drop("okey")
    return v1, v2


def active_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "supplier").filter("s_acctbal >= 0").select(F.col("s_suppkey").cast("long").alias("uid"))


def project_quota(spark: SparkSession, sf_dir: str) -> DataFrame:
    cents = F.sum(F.round(F.col("p_retailprice") * 100).cast("long"))  # whole cents: no rounding by order of addition
    return table(spark, sf_dir, "part").groupBy(F.col("p_brand").alias("project")).agg((cents * 1850).alias("quota"))


SNAPSHOTS = {"fs_large": fs_large, "fs_medium": fs_medium, "fs_small": fs_small}

_LARGE = """SELECT '/fs/r' || n_regionkey || '/n' || n_nationkey || '/u' || l_suppkey || '/' || p_type || '/' || p_brand || '/o' || l_orderkey || '_' || l_linenumber || '_' || l_partkey || '.dat' AS path,
 CASE WHEN l_linenumber = 7 THEN 'l' ELSE 'f' END AS type,
 CASE WHEN l_returnflag = 'R' AND l_linestatus = 'F' THEN 100777 WHEN l_returnflag = 'R' THEN 100600 WHEN l_returnflag = 'A' THEN 100644 ELSE 100664 END AS mode,
 CAST(l_suppkey AS BIGINT) AS uid, CAST(s_nationkey AS BIGINT) AS gid, CAST(round(l_extendedprice * 100) AS BIGINT) AS size,
 CAST(l_shipdate AS TIMESTAMP) + to_days(CAST(l_linenumber AS INT)) + to_days(CAST(l_quantity AS INT)) AS atime,
 CAST(l_shipdate AS TIMESTAMP) + to_days(CAST(l_linenumber AS INT)) AS ctime, CAST(l_shipdate AS TIMESTAMP) AS mtime,
 l_linestatus AS fileset, CAST(NULL AS VARCHAR) AS checksum, p_brand AS project, l_orderkey AS okey
 FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN part ON l_partkey = p_partkey"""
_MEDIUM = """SELECT '/proj/' || c_mktsegment || '/n' || c_nationkey || '/u' || o_custkey || '/o' || o_orderkey || '.bin' AS path, 'f' AS type,
 CASE o_orderstatus WHEN 'O' THEN 100664 WHEN 'F' THEN 100600 ELSE 100777 END AS mode, CAST(o_custkey AS BIGINT) AS uid, CAST(c_nationkey AS BIGINT) AS gid,
 CAST(round(o_totalprice * 100) AS BIGINT) AS size, CAST(o_orderdate AS TIMESTAMP) + to_days(CAST(o_orderkey % 90 AS INT)) AS atime,
 CAST(o_orderdate AS TIMESTAMP) + to_days(CAST(o_orderkey % 7 AS INT)) AS ctime, CAST(o_orderdate AS TIMESTAMP) AS mtime, c_mktsegment AS fileset,
 CAST(NULL AS VARCHAR) AS checksum, CAST(NULL AS VARCHAR) AS project FROM orders JOIN customer ON o_custkey = c_custkey"""
_SMALL = """SELECT '/home/' || source || '/' || lang || '/d' || doc_id || '.txt' AS path, 'f' AS type, CASE WHEN doc_id % 10 = 0 THEN 100777 ELSE 100644 END AS mode,
 CAST(regexp_extract(source, '(\\d+)', 1) AS BIGINT) AS uid, CAST(CASE lang WHEN 'de' THEN 1 WHEN 'en' THEN 2 WHEN 'es' THEN 3 WHEN 'fr' THEN 4 ELSE 0 END AS BIGINT) AS gid,
 CAST(strlen(text) AS BIGINT) AS size, TIMESTAMP '2024-01-01' + to_hours(doc_id) + to_days(CAST(n_chars % 60 AS INT)) AS atime,
 TIMESTAMP '2024-01-01' + to_hours(doc_id) + to_days(1) AS ctime, TIMESTAMP '2024-01-01' + to_hours(doc_id) AS mtime, CAST(NULL AS VARCHAR) AS fileset,
 md5(text) AS checksum, CASE quality WHEN 1 THEN 'good' WHEN 0 THEN 'poor' ELSE 'unlabelled' END AS project FROM documents LEFT JOIN labels USING (doc_id)"""
_URLS = """SELECT '/' || regexp_replace(url, '^[a-z]+://', '') AS path, page_id % 10 AS uid, CAST(strlen(html) AS BIGINT) AS size FROM pages"""
_CHATS = """SELECT '/chat/c' || conv_id || '/t' || turn || '.txt' AS path, 'f' AS type, conv_id % 10 AS uid, CAST(CASE role WHEN 'user' THEN 1 WHEN 'assistant' THEN 2 ELSE 3 END AS BIGINT) AS gid, CAST(strlen(text) AS BIGINT) AS size FROM conversations"""
SQL = {"fs_large": _LARGE, "fs_medium": _MEDIUM, "fs_small": _SMALL, "fs_urls": _URLS, "fs_chats": _CHATS}


def with_views(body: str, *names: str, **more: str) -> str:
    """A statement with the named views (and further ones, given as SQL) in front."""
    parts = [f"{n} AS ({SQL[n]})" for n in names] + [f"{n} AS ({q})" for n, q in more.items()]
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + body
