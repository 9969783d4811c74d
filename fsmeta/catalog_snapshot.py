"""Registered queries of the snapshot side: name -> (Spark function, DuckDB SQL or None)."""

from __future__ import annotations

from pyspark.sql import functions as F

from fsmeta import fixtures as fx
from fsmeta.fixtures import with_views
from fsmeta.functions.paths import escape_path, mode_text, unescape_path
from fsmeta.index import search as q
from fsmeta.plans import workspace
from fsmeta.sketch import base, error
from fsmeta.sketch.exact import exact_spilling
from fsmeta.snapshot import aggregate as ag
from fsmeta.snapshot import counting as ct
from fsmeta.snapshot import preprocess as pp
from fsmeta.snapshot import primary as pr
from fsmeta.snapshot import versioning as vs
from fsmeta.streaming.snapshot import AggregateEmitter

AS_OF = "2001-12-31"
QS = ag.QUANTILES
LOW, HIGH = 1, 5
R: dict = {}


def add(name: str, run, sql: str | None) -> None:
    R[name] = (run, sql)


# --- preprocessing and primary records
_red = "path, type, mode, uid, gid, size, atime, ctime, mtime, fileset"
add("preprocess_reduce", lambda s, d: pp.drop_directories(pp.reduce_columns(fx.fs_medium_raw(s, d), extra=("fileset",))), with_views(f"SELECT {_red} FROM fs_medium", "fs_medium"))
add("preprocess_escape_roundtrip", lambda s, d: fx.fs_urls(s, d).select("path", unescape_path(escape_path(F.col("path"))).alias("back"), (escape_path(F.col("path")).rlike('[,\n\t\r"#?]')).alias("unsafe")), with_views("SELECT path, path AS back, false AS unsafe FROM fs_urls", "fs_urls"))
add("preprocess_stats", lambda s, d: pp.preprocess_stats(fx.fs_medium_raw(s, d), pp.preprocess(fx.fs_medium_raw(s, d))).select("rows_in", "rows_out", "columns_in", "columns_out"), "SELECT CAST((SELECT count(*) FROM orders) + (SELECT count(*) FROM (SELECT DISTINCT c_mktsegment, c_nationkey, o_custkey FROM orders JOIN customer ON o_custkey = c_custkey)) AS BIGINT) AS rows_in, CAST((SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) AS BIGINT) AS rows_out, 12 AS columns_in, 10 AS columns_out")


def _digit(place: int) -> str:
    return f"((mode // {place}) % 10)"


def _mode_sql() -> str:
    text = "CASE type WHEN 'f' THEN '-' WHEN 'l' THEN 'l' ELSE 'd' END"
    for place, bit, on, off in ((100, 4, "s", "S"), (10, 2, "s", "S"), (1, 1, "t", "T")):
        x, e = f"({_digit(place)} & 1) > 0", f"(((mode // 1000) % 10) & {bit}) > 0"
        text += f" || CASE WHEN ({_digit(place)} & 4) > 0 THEN 'r' ELSE '-' END || CASE WHEN ({_digit(place)} & 2) > 0 THEN 'w' ELSE '-' END || CASE WHEN {e} AND {x} THEN '{on}' WHEN {e} THEN '{off}' WHEN {x} THEN 'x' ELSE '-' END"
    return text


add("mode_text", lambda s, d: fx.fs_large(s, d).groupBy("type", "mode", mode_text(F.col("type"), F.col("mode")).alias("text")).count().withColumnRenamed("count", "n"), with_views(f"SELECT type, mode, {_mode_sql()} AS text, count(*) AS n FROM fs_large GROUP BY ALL", "fs_large"))


def _records(s, d):
    r = pr.to_records(fx.fs_large(s, d))
    c = "content."
    return r.select("subject", F.array_join("visible_to", ",").alias("visible"), *[F.col(c + x).alias(x) for x in ("mode", "size", "atime", "mtime")], F.col("content.raw.mode").alias("raw_mode"))


add("primary_records", _records, with_views(f"SELECT path AS subject, 'user:' || uid || ',group:' || gid || ',group:admins' AS visible, {_mode_sql()} AS mode, size, strftime(atime, '%Y-%m-%dT%H:%M:%SZ') AS atime, strftime(mtime, '%Y-%m-%dT%H:%M:%SZ') AS mtime, mode AS raw_mode FROM fs_large", "fs_large"))
add("primary_requests", lambda s, d: pr.request_log(pr.to_requests(pr.to_records(fx.fs_large(s, d)))).agg(F.sum("n_records").alias("records"), (F.max("n_bytes") <= (10 << 20)).alias("within_limit")), with_views("SELECT CAST(count(*) AS BIGINT) AS records, true AS within_limit FROM fs_large", "fs_large"))
add("primary_submission", lambda s, d: pr.audit(pr.submit(pr.to_requests(pr.to_records(fx.fs_large(s, d)), max_bytes=1 << 20)), workspace.fresh(s, "log"), 1).agg(F.sum("n_records").alias("records"), F.bool_and(F.col("task_id").isNotNull()).alias("accepted"), F.max("tries").alias("tries")), with_views("SELECT CAST(count(*) AS BIGINT) AS records, true AS accepted, CAST(1 AS INT) AS tries FROM fs_large", "fs_large"))
add("primary_index_stats", lambda s, d: pr.index_stats(fx.fs_large(s, d)), with_views("SELECT count(*) AS records, CAST(sum(size) AS BIGINT) AS bytes, count(DISTINCT uid) AS users, count(DISTINCT gid) AS groups, count(*) FILTER (type = 'l') AS links FROM fs_large", "fs_large"))

# --- versions
_v = "SELECT * FROM fs_large WHERE mtime < TIMESTAMP '2000-01-01'"
_w = "SELECT * REPLACE (size + CASE WHEN okey % 89 = 0 THEN 1 ELSE 0 END AS size) FROM fs_large WHERE okey % 97 <> 0"
add("snapshot_diff", lambda s, d: vs.diff(*fx.versions(s, d)), with_views("SELECT coalesce(v1.path, v2.path) AS path, CASE WHEN v1.path IS NULL THEN 'create' WHEN v2.path IS NULL THEN 'delete' ELSE 'update' END AS change FROM v1 FULL JOIN v2 ON v1.path = v2.path WHERE v1.path IS NULL OR v2.path IS NULL OR v1.size <> v2.size", "fs_large", v1=_v, v2=_w))


def _latest(s, d):
    a, b = fx.versions(s, d)
    both = a.withColumn("snapshot_version", F.lit(1).cast("long")).unionByName(b.withColumn("snapshot_version", F.lit(2).cast("long")))
    return vs.latest(both).select("path", "size", "snapshot_version")


add("snapshot_latest", _latest, with_views("SELECT path, size, snapshot_version FROM (SELECT *, row_number() OVER (PARTITION BY path ORDER BY snapshot_version DESC, size DESC) AS n FROM (SELECT path, size, CAST(1 AS BIGINT) AS snapshot_version FROM v1 UNION ALL SELECT path, size, CAST(2 AS BIGINT) FROM v2)) WHERE n = 1", "fs_large", v1=_v, v2=_w))

# --- counting
_levels = "string_split(path, '/')[2:-2]"
_dirs = f"SELECT *, {_levels} AS names FROM fs_large"
_pre = "SELECT uid, gid, size, atime, ctime, mtime, path, '/' || array_to_string(names[:lvl], '/') AS dir FROM named, range(1, 6) t(lvl) WHERE lvl <= len(names)"
add("count_user", lambda s, d: ct.merge_counts(ct.shard_counts(fx.fs_large(s, d), HIGH)).filter("kind = 'user'").select("id", "n"), with_views("SELECT 'u' || uid AS id, CAST(count(*) AS BIGINT) AS n FROM fs_large GROUP BY uid", "fs_large"))
add("count_group", lambda s, d: ct.merge_counts(ct.shard_counts(fx.fs_large(s, d), HIGH)).filter("kind = 'group'").select("id", "n"), with_views("SELECT 'g' || gid AS id, CAST(count(*) AS BIGINT) AS n FROM fs_large GROUP BY gid", "fs_large"))
add("count_dir_nonrecursive", lambda s, d: ct.shard_counts(fx.fs_large(s, d), HIGH).filter("kind = 'dir'").groupBy("id").agg(F.sum("n").alias("n")), with_views("SELECT '/' || array_to_string(names[:5], '/') AS id, CAST(count(*) AS BIGINT) AS n FROM named GROUP BY 1", "fs_large", named=_dirs))
add("count_dir_recursive", lambda s, d: ct.recursive_counts(ct.shard_counts(fx.fs_large(s, d), HIGH)), with_views("SELECT '/' || array_to_string(names[:lvl], '/') AS id, CAST(count(*) AS BIGINT) AS n FROM named, range(0, 6) t(lvl) WHERE lvl <= least(5, len(names)) GROUP BY 1", "fs_large", named=_dirs))
add("count_shards", lambda s, d: ct.shard_counts(fx.fs_large(s, d), HIGH, 16).groupBy("kind", "id").agg(F.sum("n").alias("n"), (F.max("shard_id") < 16).alias("in_range")), with_views("SELECT 'user' AS kind, 'u' || uid AS id, CAST(count(*) AS BIGINT) AS n, true AS in_range FROM fs_large GROUP BY uid UNION ALL SELECT 'group', 'g' || gid, count(*), true FROM fs_large GROUP BY gid UNION ALL SELECT 'dir', '/' || array_to_string(names[:5], '/'), count(*), true FROM named GROUP BY 2", "fs_large", named=_dirs))


def _gate(s, d):
    """Rows of some sizes never arrive: the principals that lack them are told."""
    rows = fx.fs_large(s, d)
    counts, arrived = (ct.merge_counts(ct.shard_counts(r, HIGH, 16, ("user", "group")), by_shard=True) for r in (rows, rows.filter("size % 101 <> 3")))
    return ag.complete_by_shard(arrived, counts).select("kind", "id", "complete")


add("completeness_gate", _gate, with_views(" UNION ALL ".join(f"SELECT '{k}' AS kind, CAST({c} AS VARCHAR) AS id, NOT bool_or(size % 101 = 3) AS complete FROM fs_large GROUP BY {c}" for k, c in (("user", "uid"), ("group", "gid"))), "fs_large"))


def _chunks_by_source(s, d):
    """Chunks that close after whole sources only: rows, and sources found in more than one chunk."""
    at = workspace.fresh(s, "chunks")
    pp.write_chunks(fx.fs_medium(s, d).select("path", "uid", "size"), at, 400, align="source", source="uid")
    back = s.read.schema("path string, uid long, size long").option("escape", "\\").csv(at).select("uid", F.input_file_name().alias("file"))
    per = back.groupBy("uid").agg(F.count("*").alias("n"), F.countDistinct(F.regexp_extract("file", "chunk=([0-9]+)", 1)).alias("chunks"))
    return per.agg(F.sum("n").alias("n"), F.count_if(F.col("chunks") > 1).alias("cut"))


add("chunks_by_source", _chunks_by_source, with_views("SELECT CAST(count(*) AS BIGINT) AS n, CAST(0 AS BIGINT) AS cut FROM fs_medium", "fs_medium"))

# --- aggregate index
_id = {"user": "CAST(uid AS VARCHAR)", "group": "CAST(gid AS VARCHAR)", "dir": "dir"}
_from = {"user": "fs_large", "group": "fs_large", "dir": "pre"}
_num = {"size": "CAST(size AS DOUBLE)"} | {t: f"CAST(epoch({t}) AS DOUBLE)" for t in ("atime", "ctime", "mtime")}


def _agg_sql(kind: str) -> str:
    cols = ", ".join(f"min({e}) AS {a}_min, max({e}) AS {a}_max, round(avg({e}), 3) AS {a}_mean" for a, e in _num.items())
    cols += ", " + ", ".join(f"round(quantile_cont({e}, {x}), 3) AS {a}_{ag.name_of(x)}" for a, e in _num.items() for x in QS)
    return with_views(f"SELECT {_id[kind]} AS id, count(*) AS file_count, CAST(sum(size) AS DOUBLE) AS size_sum, {cols} FROM {_from[kind]} GROUP BY 1", "fs_large", named=_dirs, pre=_pre)


def _agg(kind: str, sketch: str):
    def run(s, d):
        a = ag.aggregate(fx.fs_large(s, d), LOW, HIGH, (kind,), sketch=sketch)
        names = [f"{x}_{n}" for x in ag.ATTRIBUTES for n in ("mean", *map(ag.name_of, QS))]
        drop = [f"{x}_sum" for x in ag.ATTRIBUTES[1:]]
        return a.withColumns({n: F.round(n, 3) for n in names}).drop("kind", *drop)

    return run


_dd_long = " UNION ALL ".join(f"SELECT {{id}} AS id, '{a}' AS attr, {e} AS v FROM {{src}}" for a, e in _num.items())


def _dd_sql(kind: str) -> str:
    rows = _dd_long.format(id=_id[kind], src=_from[kind])
    b = "SELECT id, attr, CASE WHEN v = 0 THEN 0 ELSE CAST(ceil(ln(v) / ln(1.01 / 0.99)) AS BIGINT) END AS bucket, count(*) AS n, min(v) AS lo, max(v) AS hi FROM melt GROUP BY 1, 2, 3"
    run = "SELECT *, sum(n) OVER (PARTITION BY id, attr ORDER BY bucket) AS upto, sum(n) OVER (PARTITION BY id, attr) AS total, min(lo) OVER (PARTITION BY id, attr) AS least_, max(hi) OVER (PARTITION BY id, attr) AS most FROM b"
    val = "2 * pow(1.01 / 0.99, bucket) / (1.01 / 0.99 + 1)"
    cols = ", ".join(f"round(least(greatest(min_by({val}, bucket) FILTER (upto > {x} * (total - 1)), min(least_)), max(most)), 3) AS {ag.name_of(x)}" for x in QS)
    return with_views(f"SELECT id, attr, {cols} FROM run GROUP BY id, attr", "fs_large", named=_dirs, pre=_pre, melt=rows, b=b, run=run)


def _dd(kind: str, after: bool = True):
    def run(s, d):
        a = ag.aggregate(fx.fs_large(s, d), LOW, HIGH, (kind,), after=after)
        rows = F.explode(F.array(*[F.struct(F.lit(x).alias("attr"), *[F.round(f"{x}_{ag.name_of(p)}", 3).alias(ag.name_of(p)) for p in QS]) for x in ag.ATTRIBUTES]))
        return a.select("id", rows.alias("x")).select("id", "x.*")

    return run


for _k in ("user", "group", "dir"):
    add(f"aggregate_exact_{_k}", _agg(_k, "exact"), _agg_sql(_k))
    add(f"dd_quantiles_{_k}", _dd(_k), _dd_sql(_k))


def _streamed(s, d):
    """The same from three micro-batches, each principal sent when its last object has come."""
    rows = fx.fs_large(s, d)
    counts = ct.merge_counts(ct.shard_counts(rows, HIGH, 16, ("user",)))
    e = AggregateEmitter(workspace.fresh(s, "streamed"), workspace.store(counts, "counts"), LOW, HIGH, ("user",))
    for epoch in range(3):
        e(rows.filter(F.col("size") % 3 == epoch), epoch)
    out = F.explode(F.array(*[F.struct(F.lit(x).alias("attr"), *[F.round(f"{x}_{ag.name_of(p)}", 3).alias(ag.name_of(p)) for p in QS]) for x in ag.ATTRIBUTES]))
    return e.emitted(s).select("id", out.alias("x")).select("id", "x.*")


add("aggregate_streamed", _streamed, _dd_sql("user"))
add("dd_expand_first_dir", _dd("dir", after=False), _dd_sql("dir"))
add("aggregate_complete", lambda s, d: ag.complete_principals(ag.totals(fx.fs_large(s, d), LOW, HIGH).select("kind", "id", "file_count"), ct.merge_counts(ct.shard_counts(fx.fs_large(s, d), HIGH))).groupBy("kind", "complete").agg(F.count("*").alias("principals")), with_views("SELECT 'user' AS kind, true AS complete, count(DISTINCT uid) AS principals FROM fs_large UNION ALL SELECT 'group', true, count(DISTINCT gid) FROM fs_large UNION ALL SELECT 'dir', true, count(DISTINCT dir) FROM pre", "fs_large", named=_dirs, pre=_pre))
add("aggregate_documents", lambda s, d: ag.to_documents(ag.aggregate(fx.fs_large(s, d))).select("subject", F.array_join("visible_to", ",").alias("visible"), F.col("content.file_count").alias("file_count"), F.col("content.size.total").alias("total")), with_views("SELECT 'user:' || uid AS subject, 'user:' || uid || ',group:admins' AS visible, count(*) AS file_count, CAST(sum(size) AS DOUBLE) AS total FROM fs_large GROUP BY uid UNION ALL SELECT 'group:' || gid, 'group:' || gid || ',group:admins', count(*), CAST(sum(size) AS DOUBLE) FROM fs_large GROUP BY gid UNION ALL SELECT 'dir:' || dir, 'public,group:admins', count(*), CAST(sum(size) AS DOUBLE) FROM pre GROUP BY dir", "fs_large", named=_dirs, pre=_pre))
add("index_sizes", lambda s, d: ct.merge_counts(ct.shard_counts(fx.fs_large(s, d), HIGH)).groupBy("kind").agg(F.count("*").alias("principals")), with_views("SELECT 'user' AS kind, count(DISTINCT uid) AS principals FROM fs_large UNION ALL SELECT 'group', count(DISTINCT gid) FROM fs_large UNION ALL SELECT 'dir', count(DISTINCT dir) FROM pre", "fs_large", named=_dirs, pre=_pre))
add("exact_spilling_user", lambda s, d: exact_spilling(ag.numbers(fx.fs_large(s, d)), ("uid",), ("size", "mtime"), QS).select("uid", "attr", *[F.round(F.get("q", i), 3).alias(ag.name_of(x)) for i, x in enumerate(QS)]), with_views(" UNION ALL ".join(f"SELECT uid, '{a}' AS attr, " + ", ".join(f"round(quantile_cont({_num[a]}, {x}), 3) AS {ag.name_of(x)}" for x in QS) + " FROM fs_large GROUP BY uid" for a in ("size", "mtime")), "fs_large"))


# --- summarizers: accuracy
def _within(algo: str, bound: float):
    """Whether every user's rank error of every attribute and quantile stays within the bound."""

    def run(s, d):
        n = ag.numbers(fx.fs_large(s, d))
        est = base.quantiles(n, ("uid",), ag.ATTRIBUTES, QS, algo)
        r = error.rank_error(n, est, ("uid",), ag.ATTRIBUTES, QS)
        return r.groupBy("uid").agg((F.max("rank_error") <= bound).alias("within_bound"), F.count("*").alias("checked"))

    return run


for _a, _b in (("kll", 0.05), ("req", 0.08), ("tdigest", 0.05), ("gk", 0.02)):
    add(f"{_a}_within_bound", _within(_a, _b), with_views("SELECT uid, true AS within_bound, CAST(24 AS BIGINT) AS checked FROM fs_large GROUP BY uid", "fs_large"))


def _dd_promise(s, d):
    """Each estimate is within alpha of the value at floor(q (n - 1)) of the sorted list."""
    n = ag.numbers(fx.fs_large(s, d))
    est = base.quantiles(n, ("uid",), ag.ATTRIBUTES, QS, "dd")
    lists = F.explode(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("v")) for a in ag.ATTRIBUTES]))
    true = n.select("uid", lists.alias("x")).groupBy("uid", F.col("x.attr").alias("attr")).agg(F.sort_array(F.collect_list("x.v")).alias("v"))
    j = true.join(est, ["uid", "attr"])
    ok = [F.abs(F.get("q", i) - F.get("v", F.floor(F.lit(x) * (F.size("v") - 1)).cast("int"))) <= 0.01 * 1.000001 * F.get("v", F.floor(F.lit(x) * (F.size("v") - 1)).cast("int")) for i, x in enumerate(QS)]
    good = ok[0]
    for o in ok[1:]:
        good = good & o
    return j.select("uid", "attr", good.alias("kept"))


add("dd_value_error", _dd_promise, with_views("SELECT DISTINCT uid, a.attr, true AS kept FROM fs_large, (VALUES ('size'), ('atime'), ('ctime'), ('mtime')) a(attr)", "fs_large"))


def _principals(s, d, view):
    """Every object under its user and its group."""
    n = ag.numbers(fx.SNAPSHOTS[view](s, d))
    both = F.array(*[F.struct(F.lit(k).alias("kind"), F.col(c).cast("long").alias("id")) for k, c in (("user", "uid"), ("group", "gid"))])
    return n.select(F.explode(both).alias("p"), *ag.ATTRIBUTES).select("p.kind", "p.id", *ag.ATTRIBUTES)


def _sweep(view):
    def run(s, d):
        df, by = _principals(s, d, view), ("kind", "id")
        out = None
        for a in ("dd", "kll", "req", "tdigest"):
            e = error.errors(df, by, ag.ATTRIBUTES, QS, a)
            out = e if out is None else out.unionByName(e)
        return out.withColumn("snapshot", F.lit(view))

    return run


for _view in ("fs_small", "fs_medium", "fs_large"):
    add(f"accuracy_{_view}", _sweep(_view), None)


def _accuracy_dd(view):
    def run(s, d):
        return error.errors(_principals(s, d, view), ("kind", "id"), ag.ATTRIBUTES, QS, "dd").select(*[F.round(c, 6).alias(c) for c in ("rank_error_min", "rank_error_max", "value_error_min", "value_error_max")])

    return run


def _accuracy_sql(view: str) -> str:
    """The default summarizer's line of the comparison: bucket estimates against exact quantiles and places."""
    rows = " UNION ALL ".join(f"SELECT '{k}' AS kind, {c} AS id, '{a}' AS attr, {e} AS v FROM {view}" for k, c in (("user", "uid"), ("group", "gid")) for a, e in _num.items())
    qs = ", ".join(f"({x}::DOUBLE)" for x in QS)
    parts = {
        "melt": f"SELECT * FROM ({rows}) m WHERE (kind, id) IN (SELECT (kind, id) FROM (SELECT 'user' AS kind, uid AS id FROM {view} UNION ALL SELECT 'group', gid FROM {view}) GROUP BY ALL HAVING count(*) >= 100)",
        "b": "SELECT kind, id, attr, CASE WHEN v = 0 THEN NULL ELSE CAST(ceil(ln(v) / ln(1.01 / 0.99)) AS BIGINT) END AS bucket, count(*) AS n FROM melt GROUP BY ALL",
        "run": "SELECT *, sum(n) OVER (PARTITION BY kind, id, attr ORDER BY bucket NULLS FIRST) AS upto, sum(n) OVER (PARTITION BY kind, id, attr) AS total FROM b",
        "e": f"SELECT kind, id, attr, q, min_by(coalesce(2 * pow(1.01 / 0.99, bucket) / (1.01 / 0.99 + 1), 0.0), upto) FILTER (upto > q * (total - 1)) AS est FROM run, (VALUES {qs}) t(q) GROUP BY ALL",
        "p": "SELECT e.kind, e.id, e.attr, e.q, any_value(est) AS est, count(*) AS n, count(*) FILTER (v < est) AS lo, count(*) FILTER (v <= est) AS hi, quantile_cont(v, [" + ", ".join(map(str, QS)) + "]) AS true_all FROM e JOIN melt USING (kind, id, attr) GROUP BY e.kind, e.id, e.attr, e.q",
        "x": "SELECT q, greatest(0.0, lo - q * n, q * n - hi) / n AS re, CASE WHEN t = est THEN 0.0 WHEN t <> 0 THEN abs(est - t) / abs(t) END AS ve FROM (SELECT *, true_all[list_position([" + ", ".join(map(str, QS)) + "]::DOUBLE[], q)] AS t FROM p)",
        "m": "SELECT q, avg(re) AS re, avg(ve) AS ve FROM x GROUP BY q",
    }
    return with_views("SELECT round(min(re), 6) AS rank_error_min, round(max(re), 6) AS rank_error_max, round(min(ve), 6) AS value_error_min, round(max(ve), 6) AS value_error_max FROM m", view, **parts)


for _view in ("fs_small", "fs_medium", "fs_large"):
    add(f"accuracy_dd_{_view}", _accuracy_dd(_view), _accuracy_sql(_view))


def _rank_dd(s, d):
    n = ag.numbers(fx.fs_large(s, d))
    est = base.quantiles(n, ("gid",), ("size",), QS, "dd")
    return error.rank_error(n, est, ("gid",), ("size",), QS, tie="right").select("gid", "quantile", F.round("rank_error", 6).alias("rank_error"))


add("dd_rank_error", _rank_dd, with_views("SELECT e.gid, e.q AS quantile, round(abs((SELECT count(*) FROM fs_large f WHERE f.gid = e.gid AND f.size <= e.est) - e.q * e.total) / e.total, 6) AS rank_error FROM e", "fs_large", b="SELECT gid, CAST(ceil(ln(CAST(size AS DOUBLE)) / ln(1.01 / 0.99)) AS BIGINT) AS bucket, count(*) AS n FROM fs_large GROUP BY 1, 2", run="SELECT *, sum(n) OVER (PARTITION BY gid ORDER BY bucket) AS upto, sum(n) OVER (PARTITION BY gid) AS total FROM b", e="SELECT gid, q, max(total) AS total, min_by(2 * pow(1.01 / 0.99, bucket) / (1.01 / 0.99 + 1), bucket) FILTER (upto > q * (total - 1)) AS est FROM run, (VALUES (0.1::DOUBLE), (0.25::DOUBLE), (0.5::DOUBLE), (0.75::DOUBLE), (0.9::DOUBLE), (0.99::DOUBLE)) t(q) GROUP BY 1, 2"))
add("sketch_footprint", lambda s, d: base.footprint(ag.numbers(fx.fs_large(s, d)), ("gid",), ("size",)), with_views("SELECT gid, 'size' AS attr, count(DISTINCT CAST(ceil(ln(CAST(size AS DOUBLE)) / ln(1.01 / 0.99)) AS BIGINT)) AS buckets, count(DISTINCT size) AS distinct_values FROM fs_large GROUP BY gid", "fs_large"))

# --- administrative questions
L = fx.fs_large
_T = f"TIMESTAMP '{AS_OF}'"
for _n, _f, _s in (
    ("q01_name", lambda s, d: q.by_name(L(s, d), "%/o12\\_%"), "SELECT path, size FROM fs_large WHERE path LIKE '%/o12\\_%' ESCAPE '\\'"),
    ("q02_world_writable", lambda s, d: q.world_writable(L(s, d)), "SELECT path, mode FROM fs_large WHERE ((mode % 10) & 2) > 0"),
    ("q03_untouched", lambda s, d: q.untouched(L(s, d), AS_OF, 12), f"SELECT path, atime FROM fs_large WHERE atime < {_T} - INTERVAL 12 MONTH"),
    ("q04_big_cold", lambda s, d: q.big_cold(L(s, d), 10_000_000, AS_OF), f"SELECT path, size FROM fs_large WHERE size > 10000000 AND atime < {_T} - INTERVAL 6 MONTH"),
    ("q05_replicas", lambda s, d: q.replicas(fx.fs_small(s, d)), "SELECT checksum, count(*) AS copies, CAST(sum(size) AS BIGINT) AS bytes FROM fs_small GROUP BY 1 HAVING count(*) > 1"),
    ("q06_over_limit", lambda s, d: q.over_limit(ct.recursive_counts(ct.shard_counts(L(s, d), 4)), 650), "SELECT '/' || array_to_string(names[:lvl], '/') AS id, CAST(count(*) AS BIGINT) AS n FROM named, range(0, 5) t(lvl) GROUP BY 1 HAVING count(*) > 650"),
    ("q07_per_project", lambda s, d: q.per_project(L(s, d)), "SELECT project, count(*) AS files, CAST(sum(size) AS BIGINT) AS bytes FROM fs_large GROUP BY 1"),
    ("q08_near_quota", lambda s, d: q.near_quota(L(s, d), fx.project_quota(s, d)), "SELECT project, used, quota, round(used / quota, 6) AS ratio FROM (SELECT project, CAST(sum(size) AS BIGINT) AS used FROM fs_large GROUP BY 1) JOIN (SELECT p_brand AS project, CAST(sum(CAST(round(p_retailprice * 100) AS BIGINT)) * 1850 AS BIGINT) AS quota FROM part GROUP BY 1) USING (project) WHERE round(used / quota, 6) > 0.9"),
    ("q09_orphans", lambda s, d: q.orphans(L(s, d), fx.active_users(s, d)), "SELECT path, uid FROM fs_large WHERE uid NOT IN (SELECT s_suppkey FROM supplier WHERE s_acctbal >= 0)"),
    ("q10_past_retention", lambda s, d: q.past_retention(L(s, d), "1996-01-01"), "SELECT path, mtime FROM fs_large WHERE mtime < TIMESTAMP '1996-01-01'"),
    ("q11_small_files", lambda s, d: q.small_files(L(s, d)), "SELECT uid, count(*) AS small_files FROM fs_large WHERE size < 1048576 GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10"),
    ("q12_per_user", lambda s, d: q.per_user(L(s, d)), "SELECT uid, count(*) AS files, CAST(sum(size) AS BIGINT) AS bytes FROM fs_large GROUP BY 1"),
    ("q13_p99_directory_project", lambda s, d: q.p99_directory(L(s, d), "project"), "SELECT project, count(*) AS dirs, round(quantile_cont(CAST(bytes AS DOUBLE), 0.99), 3) AS p99 FROM (SELECT project, path[:length(path) - length(string_split(path, '/')[-1]) - 1] AS dir, sum(size) AS bytes FROM fs_large GROUP BY 1, 2) GROUP BY 1"),
    ("q14_small_last_week", lambda s, d: q.small_last_week(L(s, d), "2001-07-01"), "SELECT uid, count(*) AS small_files FROM fs_large WHERE ctime >= TIMESTAMP '2001-06-24' AND ctime < TIMESTAMP '2001-07-01' AND size < 1048576 GROUP BY 1"),
    ("q15_p99_directory_group", lambda s, d: q.p99_directory(L(s, d), "gid"), "SELECT gid, count(*) AS dirs, round(quantile_cont(CAST(bytes AS DOUBLE), 0.99), 3) AS p99 FROM (SELECT gid, path[:length(path) - length(string_split(path, '/')[-1]) - 1] AS dir, sum(size) AS bytes FROM fs_large GROUP BY 1, 2) GROUP BY 1"),
    ("q16_top_users", lambda s, d: q.top_users(ag.totals(L(s, d), LOW, HIGH, ("user",))), "SELECT uid, CAST(sum(size) AS BIGINT) AS bytes FROM fs_large GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10"),
    ("q17_search", lambda s, d: q.search(L(s, d), [q.Match("path", "regex", "/u4[0-9]/LARGE/"), q.Match("type", "eq", "l"), q.Match("size", "gt", 9_000_000)]).select("path", "uid", "size"), "SELECT path, uid, size FROM fs_large WHERE regexp_matches(path, '/u4[0-9]/LARGE/') AND type = 'l' AND size > 9000000"),
    ("q18_summary", lambda s, d: q.summary(ag.totals(L(s, d), LOW, HIGH, ("user",)), 42), "SELECT CAST(uid AS VARCHAR) AS id, 'User ' || uid || ' owns ' || count(*) || ' files, ' || CAST(sum(size) AS BIGINT) || ' bytes in total, the largest of ' || max(size) || ' bytes.' AS summary FROM fs_large WHERE uid = 42 GROUP BY uid"),
    ("q19_visible", lambda s, d: q.visible(L(s, d), ("user:42", "group:8")).select("path", "uid", "gid"), "SELECT path, uid, gid FROM fs_large WHERE uid = 42 OR gid = 8"),
    ("q20_file_list", lambda s, d: q.past_retention(L(s, d), "1995-06-01").orderBy("path"), "SELECT path, mtime FROM fs_large WHERE mtime < TIMESTAMP '1995-06-01' ORDER BY path"),
    ("q21_owned_in", lambda s, d: q.owned_in(L(s, d), 42, "/fs/r"), "SELECT path, size FROM fs_large WHERE uid = 42 AND starts_with(path, '/fs/r/')"),
    ("q22_size_age", lambda s, d: q.size_age(L(s, d), AS_OF), f"SELECT gid, round(corr(CAST(size AS DOUBLE), (epoch({_T}) - epoch(mtime)) / 86400), 6) AS corr FROM fs_large GROUP BY 1"),
):
    add(_n, _f, with_views(_s, "fs_large", **({"named": _dirs} if "named" in _s else {})) if "fs_small" not in _s else with_views(_s, "fs_small"))
add("q21_owned_in", lambda s, d: q.search(L(s, d), [q.Match("uid", "eq", 42), q.Match("path", "regex", "^/fs/r\\d+/n\\d+/u42/LARGE/")]).select("path", "size"), with_views("SELECT path, size FROM fs_large WHERE uid = 42 AND regexp_matches(path, '^/fs/r[0-9]+/n[0-9]+/u42/LARGE/')", "fs_large"))

# --- operators around the methods
add("grouping_sets_usage", lambda s, d: L(s, d).select("uid", "gid", "size").groupingSets([["uid"], ["gid"]], "uid", "gid").agg(F.count("*").alias("files"), F.sum("size").alias("bytes")), with_views("SELECT uid, gid, count(*) AS files, CAST(sum(size) AS BIGINT) AS bytes FROM fs_large GROUP BY GROUPING SETS ((uid), (gid))", "fs_large"))
add("rollup_paths", lambda s, d: L(s, d).select(*[F.split("path", "/")[i].alias(n) for i, n in ((2, "region"), (3, "nation"), (4, "home"))], "size").rollup("region", "nation", "home").agg(F.count("*").alias("files"), F.sum("size").alias("bytes")), with_views("SELECT region, nation, home, count(*) AS files, CAST(sum(size) AS BIGINT) AS bytes FROM (SELECT string_split(path, '/')[3] AS region, string_split(path, '/')[4] AS nation, string_split(path, '/')[5] AS home, size FROM fs_large) GROUP BY ROLLUP (region, nation, home)", "fs_large"))
add("cube_usage", lambda s, d: L(s, d).cube("gid", "type", "fileset").agg(F.count("*").alias("files"), F.sum("size").alias("bytes")), with_views("SELECT gid, type, fileset, count(*) AS files, CAST(sum(size) AS BIGINT) AS bytes FROM fs_large GROUP BY CUBE (gid, type, fileset)", "fs_large"))
add("chat_usage", lambda s, d: fx.fs_chats(s, d).groupBy("gid").agg(F.count("*").alias("files"), F.sum("size").alias("bytes")), with_views("SELECT gid, count(*) AS files, CAST(sum(size) AS BIGINT) AS bytes FROM fs_chats GROUP BY 1", "fs_chats"))


def _validity(s, d):
    """Which version each object change of 1999 falls into: an interval join on versions' validity."""
    v = s.createDataFrame([(1, "1990-01-01", "1999-07-01"), (2, "1999-07-01", "2100-01-01")], "version long, begins string, ends string")
    v = v.select("version", F.col("begins").cast("timestamp_ntz").alias("begins"), F.col("ends").cast("timestamp_ntz").alias("ends"))
    p = L(s, d).filter((F.col("ctime") >= F.lit("1999-01-01").cast("timestamp_ntz")) & (F.col("ctime") < F.lit("2000-01-01").cast("timestamp_ntz")))
    return p.join(F.broadcast(v), (p.ctime >= v.begins) & (p.ctime < v.ends)).groupBy("version").agg(F.count("*").alias("files"))


def _ranked(s, d):
    from pyspark.sql import Window

    u = q.per_user(L(s, d))
    w = Window.orderBy(F.desc("bytes"), "uid")  # one row a user
    return u.select("uid", F.rank().over(w).alias("rank"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("share"))


def _top_each(s, d):
    from pyspark.sql import Window

    w = Window.partitionBy("gid").orderBy(F.desc("size"), "path")
    return L(s, d).withColumn("n", F.row_number().over(w)).filter("n <= 3").select("gid", "n", "path", "size")


def _set_ops(s, d):
    a, b = (v.select("path") for v in fx.versions(s, d))
    parts = {"both": a.intersect(b), "only_before": a.subtract(b), "only_after": b.subtract(a)}
    tagged = [p.select(F.lit(k).alias("tag")) for k, p in parts.items()]
    return tagged[0].union(tagged[1]).union(tagged[2]).agg(*[F.count_if(F.col("tag") == k).alias(k) for k in parts])


add("interval_join_versions", _validity, with_views("SELECT CAST(CASE WHEN ctime < TIMESTAMP '1999-07-01' THEN 1 ELSE 2 END AS BIGINT) AS version, count(*) AS files FROM fs_large WHERE ctime >= TIMESTAMP '1999-01-01' AND ctime < TIMESTAMP '2000-01-01' GROUP BY 1", "fs_large"))
add("users_ranked", _ranked, with_views("SELECT uid, rank() OVER w AS rank, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 9) AS share FROM (SELECT uid, sum(size) AS bytes FROM fs_large GROUP BY 1) WINDOW w AS (ORDER BY bytes DESC, uid)", "fs_large"))
add("largest_per_group", _top_each, with_views("SELECT gid, n, path, size FROM (SELECT *, CAST(row_number() OVER (PARTITION BY gid ORDER BY size DESC, path) AS INT) AS n FROM fs_large) WHERE n <= 3", "fs_large"))
add("users_per_directory", lambda s, d: q.directory_sizes(L(s, d), "uid").groupBy(F.substring_index("dir", "/", 4).alias("top")).agg(F.countDistinct("uid").alias("users")), with_views("SELECT array_to_string(string_split(path, '/')[1:4], '/') AS top, count(DISTINCT uid) AS users FROM fs_large GROUP BY 1", "fs_large"))
add("version_sets", _set_ops, with_views("SELECT (SELECT count(*) FROM (SELECT path FROM v1 INTERSECT SELECT path FROM v2)) AS \"both\", (SELECT count(*) FROM (SELECT path FROM v1 EXCEPT SELECT path FROM v2)) AS only_before, (SELECT count(*) FROM (SELECT path FROM v2 EXCEPT SELECT path FROM v1)) AS only_after", "fs_large", v1=_v, v2=_w))
add("q09_orphans_not_in", lambda s, d: s.sql("SELECT path, uid FROM {p} WHERE uid NOT IN (SELECT uid FROM {a})", p=L(s, d), a=fx.active_users(s, d)), R["q09_orphans"][1])
add("q06_aggregate_route", lambda s, d: q.search(ag.totals(L(s, d), 0, 4, ("dir",)), [q.Match("file_count", "gt", 650)]).select("id", F.col("file_count").alias("n")), R["q06_over_limit"][1])
