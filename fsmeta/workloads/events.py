"""Event workloads on the given tables, as uniform events, in Spark and in DuckDB SQL.

Uniform events: source_id, seq, ts, op, fid, is_dir, parent_fid, name, size. parent_fid and name
are set on CREATE, MKDIR and RENAME only. Ids of the four families do not meet: roots below 0,
teams, homes, directories and files each in a range of their own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Where the id ranges begin.
TEAM, HOME, DIR, FILE = 10**6, 2 * 10**6, 10**9, 10**10
OUT = "source_id, seq, ts, op, fid, is_dir, parent_fid, name, size"

_CHANGES = f"""
SELECT user_id % 5 AS source_id, event_id AS seq, ts, op, CASE family WHEN 'home' THEN {HOME} + user_id WHEN 'dir' THEN {DIR} + slot * 1000 + gen ELSE {FILE} + slot * 1000 + gen END AS fid, family <> 'file' AS is_dir,
 CASE WHEN op IN ('CREATE', 'MKDIR') THEN {HOME} + user_id WHEN op = 'RENAME' AND family = 'home' THEN {TEAM} + user_id % 10 WHEN op = 'RENAME' AND k % 2 = 0 THEN {TEAM} + user_id % 10 WHEN op = 'RENAME' THEN {HOME} + user_id END AS parent_fid,
 CASE WHEN op = 'CREATE' THEN concat('f', slot, '_', gen) WHEN op = 'MKDIR' THEN concat('d', slot, '_', gen) WHEN op = 'RENAME' AND family = 'home' THEN concat('h', user_id, '_', event_id) WHEN op = 'RENAME' THEN concat('f', slot, '_', gen, '_', event_id) END AS name,
 CASE WHEN op <> 'OPEN' THEN CAST(round(value * 1024) AS BIGINT) END AS size
FROM (SELECT *, CASE WHEN family = 'home' THEN 'RENAME' WHEN nth = 1 AND base = 'UNLINK' THEN NULL WHEN nth = 1 THEN CASE family WHEN 'dir' THEN 'MKDIR' ELSE 'CREATE' END WHEN base = 'CREATE' THEN 'SETATTR' WHEN base = 'UNLINK' AND family = 'dir' THEN 'RMDIR' ELSE base END AS op
 FROM (SELECT *, row_number() OVER (PARTITION BY family, slot, gen ORDER BY event_id) AS nth
  FROM (SELECT *, CAST(coalesce(sum(CASE WHEN base = 'UNLINK' THEN 1 ELSE 0 END) OVER (PARTITION BY family, slot ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS gen
   FROM (SELECT *, user_id * 4 + k % 4 AS slot,
     CASE WHEN event_type = 'purchase' AND k = 0 THEN 'home' WHEN event_type IN ('signup', 'error') AND k >= 90 THEN 'dir' ELSE 'file' END AS family,
     CASE event_type WHEN 'signup' THEN 'CREATE' WHEN 'view' THEN 'OPEN' WHEN 'click' THEN 'CLOSE' WHEN 'purchase' THEN CASE WHEN k < 20 THEN 'RENAME' ELSE 'SETATTR' END ELSE 'UNLINK' END AS base
    FROM (SELECT event_id, ts, user_id, event_type, value, CAST(KEY_OF AS BIGINT) AS k FROM events) a) b) c) d) e
WHERE op IS NOT NULL"""
_TREE = f"""
SELECT DISTINCT user_id % 5 AS source_id, -1 - user_id % 5 AS fid, CAST(NULL AS BIGINT) AS parent_fid, concat('s', user_id % 5) AS name, true AS is_dir, CAST(NULL AS BIGINT) AS size FROM events
UNION SELECT DISTINCT user_id % 5, {TEAM} + user_id % 10, -1 - user_id % 5, concat('t', user_id % 10), true, CAST(NULL AS BIGINT) FROM events
UNION SELECT DISTINCT user_id % 5, {HOME} + user_id, {TEAM} + user_id % 10, concat('h', user_id), true, CAST(NULL AS BIGINT) FROM events"""
_MIXED = """
SELECT o_custkey % SOURCES AS source_id, o_orderkey * 8 + step AS seq, o_orderdate AS ts, op, CASE WHEN op IN ('MKDIR', 'RMDIR') THEN o_orderkey * 2 + 1 ELSE o_orderkey * 2 END AS fid, op IN ('MKDIR', 'RMDIR') AS is_dir,
 CASE WHEN step IN (0, 3, 4) THEN -1 - o_custkey % SOURCES WHEN step = 5 THEN o_orderkey * 2 + 1 END AS parent_fid,
 CASE step WHEN 0 THEN concat('hello', o_orderkey) WHEN 3 THEN concat('hi', o_orderkey) WHEN 4 THEN concat('okdir', o_orderkey) WHEN 5 THEN concat('hi', o_orderkey) END AS name,
 CAST(round(o_totalprice) AS BIGINT) AS size
FROM orders, (VALUES (0, 'CREATE'), (1, 'OPEN'), (2, 'CLOSE'), (3, 'RENAME'), (4, 'MKDIR'), (5, 'RENAME'), (6, 'UNLINK'), (7, 'RMDIR')) AS t(step, op)"""
_CYCLE = """
SELECT user_id % SOURCES AS source_id, event_id * 4 + step AS seq, ts, op, event_id AS fid, false AS is_dir, CASE WHEN step = 0 THEN -1 - user_id % SOURCES END AS parent_fid,
 CASE WHEN step = 0 THEN concat('f', event_id) END AS name, CAST(round(value) AS BIGINT) AS size
FROM events, (VALUES (0, 'CREATE'), (1, 'OPEN'), (2, 'CLOSE'), (3, 'UNLINK')) AS t(step, op)"""
_READ = """
SELECT user_id % SOURCES AS source_id, event_id * 2 + step AS seq, ts, op, fid, false AS is_dir, CAST(NULL AS BIGINT) AS parent_fid, CAST(NULL AS VARCHAR(100)) AS name, CAST(NULL AS BIGINT) AS size
FROM (SELECT user_id, event_id, ts, 3000000 + (event_id * 2654435761) % (SELECT count(DISTINCT l_partkey) FROM lineitem) AS fid FROM events) e, (VALUES (0, 'OPEN'), (1, 'CLOSE')) AS t(step, op)"""

#: Sizes of 16 KB on average: twenty quantiles of a Gamma distribution of shape 1.5, worked out once from the mean.
GAMMA_SIZES = tuple(int(16_384 * x) for x in (0.06, 0.13, 0.19, 0.25, 0.31, 0.38, 0.45, 0.52, 0.59, 0.68, 0.77, 0.86, 0.97, 1.09, 1.22, 1.39, 1.60, 1.88, 2.31, 3.35))

SQL = {
    "changes": _CHANGES.replace("KEY_OF", "json_extract(props, '$.k')"),
    "changes_tree": _TREE,
    **{f"{n}_{m}": q.replace("SOURCES", str(m)) for n, q in (("mixed_ops", _MIXED), ("create_delete", _CYCLE), ("tree_read", _READ)) for m in (1, 2, 3, 4, 5)},
}


def _view(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    tables = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("events", "orders", "lineitem") if t in sql}
    for t, df in tables.items():
        sql = _named(sql, t, f"{{{t}}}")
    return spark.sql(sql, **tables)


def _named(sql: str, word: str, by: str) -> str:
    import re

    return re.sub(rf"\b(FROM|,) {word}\b", rf"\1 {by}", sql)


def changes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _view(spark, sf_dir, _CHANGES.replace("KEY_OF", "get_json_object(props, '$.k')"))


def changes_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directories that exist before the events: source_id, fid, parent_fid, name, is_dir, size."""
    return _view(spark, sf_dir, _TREE)


def mixed_ops(spark: SparkSession, sf_dir: str, sources: int = 1) -> DataFrame:
    return _view(spark, sf_dir, _MIXED.replace("SOURCES", str(sources)))


def create_delete(spark: SparkSession, sf_dir: str, sources: int = 1) -> DataFrame:
    return _view(spark, sf_dir, _CYCLE.replace("SOURCES", str(sources)))


def tree_read(spark: SparkSession, sf_dir: str, sources: int = 1) -> DataFrame:
    return _view(spark, sf_dir, _READ.replace("SOURCES", str(sources)))


def roots(events: DataFrame) -> DataFrame:
    """The root directory of every source."""
    return events.select("source_id").distinct().selectExpr("source_id", "-1 - source_id AS fid", "CAST(NULL AS BIGINT) AS parent_fid", "concat('s', source_id) AS name", "true AS is_dir", "CAST(NULL AS BIGINT) AS size")


def read_tree(spark: SparkSession, sf_dir: str, sources: int = 1) -> DataFrame:
    """The populated tree of the read workload: three directory levels by base-20 digits, one file a part.
    Parts are numbered by running sums: those of buckets of keys first, then inside each bucket."""
    parts = spark.read.parquet(f"{sf_dir}/lineitem.parquet").selectExpr("l_partkey AS p", "floor(l_partkey / 4096) AS bucket").distinct()
    before = parts.groupBy("bucket").count().selectExpr("bucket", "coalesce(sum(count) OVER (ORDER BY bucket ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS base")
    parts = parts.join(before, "bucket").selectExpr("p", "base + row_number() OVER (PARTITION BY bucket ORDER BY p) - 1 AS i")
    every = f"explode(sequence(CAST(0 AS BIGINT), {sources - 1})) AS source_id"
    top = spark.range(sources).withColumnRenamed("id", "source_id").selectExpr("source_id", "-1 - source_id AS fid", "CAST(NULL AS BIGINT) AS parent_fid", "concat('s', source_id) AS name", "true AS is_dir", "CAST(NULL AS BIGINT) AS size")
    keys = parts.selectExpr("i", "p % 20 AS a", "floor(p / 20) % 20 AS b", "floor(p / 400) % 20 AS c")
    sizes = ", ".join(map(str, GAMMA_SIZES))
    out = top
    for level, (fid, parent, name) in enumerate((("100 + a", "-1 - source_id", "a"), ("10000 + a * 20 + b", "100 + a", "b"), ("1000000 + a * 400 + b * 20 + c", "10000 + a * 20 + b", "c"))):
        cols = "abc"[: level + 1]
        out = out.union(keys.select(*cols).distinct().selectExpr("*", every).selectExpr("source_id", f"CAST({fid} AS BIGINT) AS fid", f"CAST({parent} AS BIGINT) AS parent_fid", f"concat('d', {name}) AS name", "true AS is_dir", "CAST(NULL AS BIGINT) AS size"))
    files = keys.selectExpr("*", every).selectExpr("source_id", "CAST(3000000 + i AS BIGINT) AS fid", "CAST(1000000 + a * 400 + b * 20 + c AS BIGINT) AS parent_fid", "concat('f', i) AS name", "false AS is_dir", f"CAST(element_at(array({sizes}), CAST(i % 20 + 1 AS INT)) AS BIGINT) AS size")
    return out.union(files)
