"""Registered queries of the event side: name -> (Spark function, DuckDB SQL or None)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from fsmeta.index import store
from fsmeta.monitor import baseline, batching, ingest, notify, run, setbased
from fsmeta.monitor import reduce as rd
from fsmeta.plans import workspace
from fsmeta.snapshot import versioning
from fsmeta.workloads import events as ev

R: dict = {}
BATCH, LONG = 100, "100000 days"


def add(name: str, run_, sql: str | None) -> None:
    R[name] = (run_, sql)


def _batched(s, d, max_events=BATCH):
    return batching.assign_batches(ingest.filter_low_information(ev.changes(s, d)), max_events, LONG)


_C = ev.SQL["changes"]
_B = "SELECT *, CAST((row_number() OVER (PARTITION BY source_id ORDER BY seq) - 1) // {n} AS BIGINT) AS batch_id FROM {src} WHERE op <> 'OPEN'"
_RAW = "SELECT source_id, batch_id FROM b WHERE op = 'RENAME' AND is_dir GROUP BY ALL"
_G = """SELECT b.source_id, b.batch_id, fid, max(seq) AS seq, count(*) AS events, arg_min(op, seq) AS first_op, arg_max(op, seq) AS last_op, bool_or(op = 'RENAME') AS renamed, arg_max(is_dir, seq) AS is_dir,
 arg_max(parent_fid, seq) FILTER (op IN ('CREATE', 'MKDIR', 'RENAME')) AS parent_fid, arg_max(name, seq) FILTER (op IN ('CREATE', 'MKDIR', 'RENAME')) AS name, arg_max(size, seq) FILTER (size IS NOT NULL) AS size
 FROM b LEFT JOIN raw ON b.source_id = raw.source_id AND b.batch_id = raw.batch_id WHERE raw.batch_id IS NULL GROUP BY b.source_id, b.batch_id, fid"""
_CANCEL = "(first_op = 'CREATE' AND last_op = 'UNLINK' OR first_op = 'MKDIR' AND last_op = 'RMDIR')"
_S = f"""SELECT source_id, batch_id, seq, CASE WHEN last_op IN ('UNLINK', 'RMDIR') THEN last_op WHEN first_op IN ('CREATE', 'MKDIR') THEN first_op WHEN renamed THEN 'RENAME' ELSE 'SETATTR' END AS op, fid, is_dir, parent_fid, name, size FROM g WHERE NOT {_CANCEL}
 UNION ALL SELECT b.source_id, b.batch_id, seq, op, fid, is_dir, parent_fid, name, size FROM b JOIN raw ON b.source_id = raw.source_id AND b.batch_id = raw.batch_id"""


def stack(body: str, src: str = _C, n: int = BATCH, **more: str) -> str:
    parts = {"c": src, "b": _B.format(n=n, src="c"), "raw": _RAW, "g": _G, "s": _S, **more}
    return "WITH RECURSIVE " + ",\n".join(f"{k} AS ({v})" for k, v in parts.items()) + "\n" + body


_cols = "source_id, seq, op, fid, is_dir, parent_fid, name, size"
add("event_uniform_watch", lambda s, d: ingest.to_uniform(ingest.render_watch(ev.changes(s, d)), "watch").drop("ts"), stack(f"SELECT {_cols} FROM c"))
add("event_uniform_changelog", lambda s, d: ingest.to_uniform(ingest.render_changelog(ev.changes(s, d)), "changelog").drop("ts", "size"), stack(f"SELECT {_cols.removesuffix(', size')} FROM c"))
add("event_filter", lambda s, d: ingest.filter_low_information(ev.changes(s, d)).groupBy("op").agg(F.count("*").alias("events")), stack("SELECT op, count(*) AS events FROM c WHERE op <> 'OPEN' GROUP BY 1"))
add("event_batches", lambda s, d: _batched(s, d).groupBy("source_id", "batch_id").agg(F.count("*").alias("events"), F.min("seq").alias("first"), F.max("seq").alias("last")), stack("SELECT source_id, batch_id, count(*) AS events, min(seq) AS first, max(seq) AS last FROM b GROUP BY 1, 2"))
add("session_batches", lambda s, d: batching.assign_batches(ev.changes(s, d), 1000, "15 minutes").groupBy("source_id").agg((F.max("batch_id") + 1).alias("batches"), F.count("*").alias("events")), stack("SELECT source_id, CAST(count(DISTINCT (sess, chunk)) AS BIGINT) AS batches, count(*) AS events FROM (SELECT *, (row_number() OVER (PARTITION BY source_id, sess ORDER BY seq) - 1) // 1000 AS chunk FROM (SELECT *, sum(CAST(gap AS INT)) OVER (PARTITION BY source_id ORDER BY seq) AS sess FROM (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY source_id ORDER BY seq) > INTERVAL 15 MINUTE, false) AS gap FROM c))) GROUP BY 1"))
add("event_coalesce", lambda s, d: rd.coalesced(_batched(s, d)).select("source_id", "batch_id", "fid", "seq", "events", "first_op", "last_op"), stack("SELECT source_id, batch_id, fid, max(seq) AS seq, count(*) AS events, arg_min(op, seq) AS first_op, arg_max(op, seq) AS last_op FROM b GROUP BY 1, 2, 3"))
add("event_cancel_file", lambda s, d: rd.coalesced(_batched(s, d)).filter(rd.CANCEL_FILE.drops()).select("source_id", "batch_id", "fid"), stack("SELECT source_id, batch_id, fid FROM (SELECT source_id, batch_id, fid, arg_min(op, seq) AS f, arg_max(op, seq) AS l FROM b GROUP BY 1, 2, 3) WHERE f = 'CREATE' AND l = 'UNLINK'"))
add("event_cancel_dir", lambda s, d: rd.coalesced(_batched(s, d)).filter(rd.CANCEL_DIR.drops()).select("source_id", "batch_id", "fid"), stack("SELECT source_id, batch_id, fid FROM (SELECT source_id, batch_id, fid, arg_min(op, seq) AS f, arg_max(op, seq) AS l FROM b GROUP BY 1, 2, 3) WHERE f = 'MKDIR' AND l = 'RMDIR'"))
add("event_rename_override", lambda s, d: _batched(s, d).filter(rd.dir_rename()).select("source_id", "batch_id").distinct(), stack("SELECT source_id, batch_id FROM raw"))
add("event_reduce", lambda s, d: rd.reduce(_batched(s, d)).drop("ts"), stack("SELECT * FROM s"))
add("event_reduce_barrier", lambda s, d: rd.reduce(_batched(s, d), override="barrier").groupBy("source_id").agg(F.count("*").alias("events")), stack("SELECT source_id, count(*) AS events FROM (SELECT source_id FROM (SELECT source_id, batch_id, part, fid, arg_min(op, seq) AS first_op, arg_max(op, seq) AS last_op FROM p WHERE NOT dr GROUP BY 1, 2, 3, 4) WHERE NOT " + _CANCEL + " UNION ALL SELECT source_id FROM p WHERE dr) GROUP BY 1", p="SELECT *, sum(CAST(dr AS INT)) OVER (PARTITION BY source_id, batch_id ORDER BY seq) AS part FROM (SELECT *, op = 'RENAME' AND is_dir AS dr FROM b)"))
add("event_reduce_stats", lambda s, d: rd.reduce_stats(_batched(s, d), rd.reduce(_batched(s, d)), ev.changes(s, d)), stack("SELECT source_id, (SELECT count(*) FROM b WHERE b.source_id = x.source_id) AS events_in, (SELECT count(*) FROM s WHERE s.source_id = x.source_id) AS events_out, (SELECT count(*) FROM g WHERE g.source_id = x.source_id AND first_op = 'CREATE' AND last_op = 'UNLINK') AS cancelled_files, (SELECT count(*) FROM g WHERE g.source_id = x.source_id AND first_op = 'MKDIR' AND last_op = 'RMDIR') AS cancelled_dirs, CAST((SELECT coalesce(sum(events - 1), 0) FROM g WHERE g.source_id = x.source_id AND NOT " + _CANCEL + ") AS BIGINT) AS coalesced, CAST((SELECT coalesce(sum(events), 0) FROM g WHERE g.source_id = x.source_id AND " + _CANCEL + ") AS BIGINT) AS cancelled_events, (SELECT count(*) FROM c WHERE c.source_id = x.source_id AND op = 'OPEN') AS opens_dropped FROM (SELECT DISTINCT source_id FROM c) x"))

# --- hierarchy: node tables after the events up to a sequence, and their paths
_AFTER = """SELECT coalesce(t.source_id, l.source_id) AS source_id, coalesce(t.fid, l.fid) AS fid, coalesce(l.parent_fid, t.parent_fid) AS parent_fid, coalesce(l.name, t.name) AS name, coalesce(t.is_dir, l.is_dir) AS is_dir, l.size, l.last_seq
 FROM tree t FULL JOIN (SELECT source_id, fid, arg_max(op, seq) AS op, max(seq) AS last_seq, arg_max(is_dir, seq) AS is_dir, arg_max(parent_fid, seq) FILTER (parent_fid IS NOT NULL) AS parent_fid, arg_max(name, seq) FILTER (parent_fid IS NOT NULL) AS name, arg_max(size, seq) FILTER (size IS NOT NULL) AS size FROM {ev} GROUP BY 1, 2) l ON t.source_id = l.source_id AND t.fid = l.fid
 WHERE coalesce(l.op, '') NOT IN ('UNLINK', 'RMDIR') AND coalesce(l.name, t.name) IS NOT NULL"""
_PATHS = "SELECT source_id, fid, is_dir, size, last_seq, '/' || name AS path FROM {n} WHERE parent_fid IS NULL UNION ALL SELECT n.source_id, n.fid, n.is_dir, n.size, n.last_seq, p.path || '/' || n.name FROM {n} n JOIN {p} p ON n.source_id = p.source_id AND n.parent_fid = p.fid WHERE p.is_dir"
_FULL = {"tree": ev.SQL["changes_tree"], "n1": _AFTER.format(ev="c"), "p1": _PATHS.format(n="n1", p="p1")}


def _after(s, d, events=None):
    return setbased.resolve_paths(setbased.apply_events(ev.changes_tree(s, d), ev.changes(s, d) if events is None else events))


add("path_resolve", lambda s, d: _after(s, d).select("source_id", "fid", "path"), stack("SELECT source_id, fid, path FROM p1", **_FULL))
add("index_after_events", lambda s, d: setbased.index_of(_after(s, d, rd.reduce(_batched(s, d)))), stack("SELECT source_id, fid, path, size FROM p1 WHERE NOT is_dir", **_FULL))
add("index_after_raw_events", lambda s, d: setbased.index_of(_after(s, d)), stack("SELECT source_id, fid, path, size FROM p1 WHERE NOT is_dir", **_FULL))


def _empty(s):
    return s.createDataFrame([], "path string, source_id long, fid long, size long, last_seq long")


def _stateful(reduce):
    return lambda s, d: store.apply(_empty(s), run.monitor(ev.changes(s, d), ev.changes_tree(s, d), reduce, BATCH)).select("source_id", "fid", "path", "size")


add("monitor_stateful_reduced", _stateful(True), stack("SELECT source_id, fid, path, size FROM p1 WHERE NOT is_dir", **_FULL))
add("monitor_stateful", _stateful(False), stack("SELECT source_id, fid, path, size FROM p1 WHERE NOT is_dir", **_FULL))
_half = "(SELECT max(seq) / 2 FROM c)"
_TWO = {"tree": ev.SQL["changes_tree"], "c1": f"SELECT * FROM c WHERE seq <= {_half}", "na": _AFTER.format(ev="c1"), "pa": _PATHS.format(n="na", p="pa"), "n1": _AFTER.format(ev="c"), "p1": _PATHS.format(n="n1", p="p1")}


def _lists(s, d):
    c = ev.changes(s, d)
    cut = c.agg((F.max("seq") / 2).alias("m")).first()["m"]
    before = setbased.apply_events(ev.changes_tree(s, d), c.filter(F.col("seq") <= cut)).drop("last_seq")
    after = setbased.apply_events(before, c.filter(F.col("seq") > cut))
    return setbased.actions(setbased.resolve_paths(before), setbased.resolve_paths(after))


add("to_update", lambda s, d: _lists(s, d).filter("action = 'update'").select("source_id", "fid", "path", "size"), stack(f"SELECT p1.source_id, p1.fid, p1.path, p1.size FROM p1 LEFT JOIN pa ON p1.source_id = pa.source_id AND p1.fid = pa.fid WHERE NOT p1.is_dir AND (pa.path IS DISTINCT FROM p1.path OR (p1.source_id, p1.fid) IN (SELECT (source_id, fid) FROM c WHERE seq > {_half}))", **_TWO))
add("to_delete", lambda s, d: _lists(s, d).filter("action = 'delete'").select("source_id", "fid", "path"), stack("SELECT pa.source_id, pa.fid, pa.path FROM pa LEFT JOIN p1 ON p1.source_id = pa.source_id AND p1.fid = pa.fid WHERE NOT pa.is_dir AND pa.path IS DISTINCT FROM p1.path", **_TWO))


def _stateful_files(s, d):
    """The index after the second half of the events; the node table has the files of the first half."""
    c = ev.changes(s, d)
    cut = c.agg((F.max("seq") / 2).alias("m")).first()["m"]
    before = setbased.apply_events(ev.changes_tree(s, d), c.filter(F.col("seq") <= cut)).drop("last_seq")
    a = run.monitor(c.filter(F.col("seq") > cut), before, True, BATCH)
    index = setbased.index_of(setbased.resolve_paths(before)).withColumn("last_seq", F.lit(-1).cast("long"))
    return store.apply(index, a).select("source_id", "fid", "path", "size")


def _evicted(s, d):
    """The same with room for five directories a source."""
    a = run.monitor(ev.changes(s, d), ev.changes_tree(s, d), True, BATCH, max_dirs=5)
    return store.apply(_empty(s), a).select("source_id", "fid", "path", "size")


def _looked_up(s, d):
    """The same without a node table: directories come from a resolver."""
    a = run.monitor(ev.changes(s, d), None, True, BATCH, resolver=run.table_resolver(ev.changes_tree(s, d)))
    return store.apply(_empty(s), a).select("source_id", "fid", "path", "size")


_INDEX = stack("SELECT source_id, fid, path, size FROM p1 WHERE NOT is_dir", **_FULL)
add("evicted_state", _evicted, _INDEX)
add("root_lookups", _looked_up, _INDEX)
# of the directories that exist before the events, those that an event names are each looked up once, and their ancestors
add("root_lookup_counts", lambda s, d: run.costs(ev.create_delete(s, d, 2), None, False, 300, resolver=run.table_resolver(ev.roots(ev.create_delete(s, d, 2)))).select("source_id", "lookups", "unresolved", "updates"), stack("SELECT source_id, CAST(1 AS BIGINT) AS lookups, CAST(0 AS BIGINT) AS unresolved, CAST(sum(updates) AS BIGINT) AS updates FROM (SELECT source_id, batch_id, count(DISTINCT fid) FILTER (last <> 'UNLINK') AS updates FROM (SELECT source_id, batch_id, fid, arg_max(op, seq) AS last FROM b GROUP BY 1, 2, 3) GROUP BY 1, 2) GROUP BY 1", ev.SQL["create_delete_2"], 300))
# without node table and resolver, creations and updates of files show nothing and are counted
add("unresolved_events", lambda s, d: run.costs(ev.create_delete(s, d, 2), None, False, 300).select("source_id", "events_in", "unresolved", "updates", "deletes"), stack("SELECT source_id, count(*) AS events_in, count(*) FILTER (op IN ('CREATE', 'CLOSE')) AS unresolved, CAST(0 AS BIGINT) AS updates, CAST(0 AS BIGINT) AS deletes FROM c GROUP BY 1", ev.SQL["create_delete_2"], 300))


def _unified(s, d):
    """A snapshot after the first half of the events, then all events again, those that it covers passed over."""
    from fsmeta import session

    c = ev.changes(s, d)
    cut = {r["source_id"]: r["m"] for r in c.groupBy("source_id").agg(F.expr("CAST(max(seq) / 2 AS BIGINT)").alias("m")).collect()}  # a row a source
    at = s.createDataFrame(sorted(cut.items()), "source_id long, at long")
    nodes = workspace.store(setbased.apply_events(ev.changes_tree(s, d), c.join(F.broadcast(at), "source_id").filter("seq <= at").drop("at")).drop("last_seq"), "nodes")
    files = setbased.index_of(setbased.resolve_paths(nodes))
    one = session.open(s, workspace.fresh(s, "unified"), max_events=BATCH, idle="100000 days")
    versioning.publish(files, f"{one.path}/primary", 1, cut)
    one.notify(one.monitor(c, nodes), 0)
    one.notify(one.monitor(c, nodes), 1)  # replayed
    return one.index(one.primary()).select("source_id", "fid", "path", "size")


add("index_unified", _unified, _INDEX)
add("monitor_stateful_files", _stateful_files, stack("SELECT source_id, fid, path, size FROM p1 WHERE NOT is_dir", **_FULL))


def _descendants(s, d):
    c = ev.changes(s, d)
    plain = c.filter(~rd.dir_rename())
    before, after = _after(s, d, plain), _after(s, d)
    b = before.select("source_id", "fid", F.col("path").alias("old"))
    return after.filter(~F.col("is_dir")).join(b, ["source_id", "fid"]).filter("old <> path").select("source_id", "fid", "old", "path")


add("dir_rename_descendants", _descendants, stack("SELECT p1.source_id, p1.fid, pb.path AS old, p1.path FROM p1 JOIN pb ON p1.source_id = pb.source_id AND p1.fid = pb.fid WHERE NOT p1.is_dir AND pb.path <> p1.path", **_FULL, cp="SELECT * FROM c WHERE NOT (op = 'RENAME' AND is_dir)", nb=_AFTER.format(ev="cp"), pb=_PATHS.format(n="nb", p="pb")))
# one list entry for each change that a batch leaves: unreduced, every file event but its opens shows something
add("notify_requests", lambda s, d: notify.to_requests(run.monitor(ev.create_delete(s, d, 2), ev.roots(ev.create_delete(s, d, 2)), False, 301), 100).groupBy("source_id", "kind").agg(F.sum("n_records").alias("records"), F.count("*").alias("requests")), stack("SELECT source_id, kind, CAST(sum(n) AS BIGINT) AS records, CAST(sum(ceil(n / 100)) AS BIGINT) AS requests FROM (SELECT source_id, batch_id, 'ingest' AS kind, count(*) FILTER (last <> 'UNLINK') AS n FROM l GROUP BY 1, 2 UNION ALL SELECT source_id, batch_id, 'delete', count(*) FILTER (last = 'UNLINK') FROM l GROUP BY 1, 2) WHERE n > 0 GROUP BY 1, 2", ev.SQL["create_delete_2"], 301, l="SELECT source_id, batch_id, fid, arg_max(op, seq) AS last FROM b GROUP BY 1, 2, 3"))
add("monitor_costs", lambda s, d: run.costs(ev.changes(s, d), ev.changes_tree(s, d), True, BATCH).select("source_id", "events_in", "opens_dropped", "cancelled_files", "cancelled_dirs", "coalesced", "overrides"), stack("SELECT source_id, (SELECT count(*) FROM c WHERE c.source_id = x.source_id) AS events_in, (SELECT count(*) FROM c WHERE c.source_id = x.source_id AND op = 'OPEN') AS opens_dropped, (SELECT count(*) FROM g WHERE g.source_id = x.source_id AND first_op = 'CREATE' AND last_op = 'UNLINK') AS cancelled_files, (SELECT count(*) FROM g WHERE g.source_id = x.source_id AND first_op = 'MKDIR' AND last_op = 'RMDIR') AS cancelled_dirs, CAST((SELECT coalesce(sum(events - 1), 0) FROM g WHERE g.source_id = x.source_id AND NOT " + _CANCEL + ") AS BIGINT) AS coalesced, (SELECT count(*) FROM raw WHERE raw.source_id = x.source_id) AS overrides FROM (SELECT DISTINCT source_id FROM c) x"))

# --- baselines and workloads
add("passthrough", lambda s, d: baseline.passthrough(ev.changes(s, d)).groupBy("source_id").agg(F.count("*").alias("events")), stack("SELECT source_id, count(*) AS events FROM c GROUP BY 1"))
_CALLS = "SELECT source_id, count(*) AS events, count(*) FILTER (miss) AS calls, count(*) FILTER (NOT miss) AS hits FROM (SELECT source_id, coalesce(lag(op) OVER (PARTITION BY source_id, fid ORDER BY seq) IN ('UNLINK', 'RMDIR', 'RENAME'), true) AS miss FROM c) GROUP BY 1"
add("lookup_baseline_counts", lambda s, d: baseline.per_event_lookup(ev.changes(s, d)).drop("modelled_s"), stack(_CALLS))
_COUNTS = "SELECT source_id, (SELECT count(DISTINCT batch_id) FROM b WHERE b.source_id = x.source_id) AS batches, (SELECT count(*) FROM b WHERE b.source_id = x.source_id) AS events_in, (SELECT count(*) FROM s WHERE s.source_id = x.source_id) AS events_out, (SELECT count(*) FROM g WHERE g.source_id = x.source_id AND first_op = 'CREATE' AND last_op = 'UNLINK') AS cancelled_files, (SELECT count(*) FROM g WHERE g.source_id = x.source_id AND first_op = 'MKDIR' AND last_op = 'RMDIR') AS cancelled_dirs, CAST((SELECT coalesce(sum(events - 1), 0) FROM g WHERE g.source_id = x.source_id AND NOT " + _CANCEL + ") AS BIGINT) AS coalesced FROM (SELECT DISTINCT source_id FROM c) x"


def _reduced_counts(make, sources, n):
    def run_(s, d):
        b = batching.assign_batches(ingest.filter_low_information(make(s, d, sources)), n, LONG)
        return rd.batch_stats(b).drop("cancelled_events")

    return run_


# batch sizes that the scripts' steps do not divide: pairs cut by a batch's end survive
add("lookup_pipeline", lambda s, d: store.apply(_empty(s), baseline.lookup_pipeline(ev.changes(s, d), ev.changes_tree(s, d), wait_s=0.0, drop=("OPEN",))).select("source_id", "fid", "path", "size"), _INDEX)
add("lookup_pipeline_calls", lambda s, d: baseline.lookup_pipeline(ev.create_delete(s, d, 2), ev.roots(ev.create_delete(s, d, 2)), wait_s=0.0, want="costs").select("source_id", F.col("events_in").alias("events"), F.col("lookups").alias("calls"), F.col("lookup_hits").alias("hits")), stack(_CALLS, ev.SQL["create_delete_2"]))
_LAG = "epoch(applied) - epoch(ts)"
add("freshness_lag", lambda s, d: store.freshness(ev.changes(s, d).withColumn("applied", F.col("ts") + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.col("seq") % 97))), stack(f"SELECT quantile_cont({_LAG}, 0.5) AS p50, quantile_cont({_LAG}, 0.99) AS p99 FROM (SELECT ts, ts + to_seconds(seq % 97) AS applied FROM c)"))
for _w, _f, _n in (("mixed_ops", ev.mixed_ops, 704), ("create_delete", ev.create_delete, 301), ("tree_read", ev.tree_read, 1000)):
    for _m in (1, 2, 4):
        add(f"{_w}_reduce_{_m}", _reduced_counts(_f, _m, _n), stack(_COUNTS, ev.SQL[f"{_w}_{_m}"], _n))
    add(f"{_w}_lookups", lambda s, d, f=_f: baseline.per_event_lookup(f(s, d, 1)).drop("modelled_s"), stack(_CALLS, ev.SQL[f"{_w}_1"]))
for _m in (1, 2, 3, 4, 5):
    add(f"filesets_{_m}", lambda s, d, m=_m: run.costs(ev.create_delete(s, d, m), ev.roots(ev.create_delete(s, d, m)), True, 300).select("source_id", "events_in", "opens_dropped", "cancelled_files"), stack("SELECT source_id, count(*) AS events_in, count(*) FILTER (op = 'OPEN') AS opens_dropped, (SELECT count(*) FROM g WHERE g.source_id = c.source_id AND first_op = 'CREATE' AND last_op = 'UNLINK') AS cancelled_files FROM c GROUP BY source_id", ev.SQL[f"create_delete_{_m}"], 300))
add("tree_read_stateful", lambda s, d: run.costs(ev.tree_read(s, d, 1), ev.read_tree(s, d, 1), True, 1000, stat_mode="call").select("source_id", "events_in", "opens_dropped", "updates", "stat_calls"), stack("SELECT source_id, count(*) AS events_in, count(*) FILTER (op = 'OPEN') AS opens_dropped, (SELECT count(*) FROM s) AS updates, (SELECT count(*) FROM s) AS stat_calls FROM c GROUP BY source_id", ev.SQL["tree_read_1"], 1000))


def _partitions(parts):
    return lambda s, d: run.costs(ev.changes(s, d).repartition(parts), ev.changes_tree(s, d), True, BATCH).agg(F.sum("events_in").alias("events"), F.sum("cancelled_files").alias("cancelled"))


for _p in (1, 2, 4, 8, 16):
    add(f"partitions_{_p}", _partitions(_p), stack("SELECT CAST((SELECT count(*) FROM c) AS BIGINT) AS events, CAST((SELECT count(*) FROM g WHERE first_op = 'CREATE' AND last_op = 'UNLINK') AS BIGINT) AS cancelled"))

# --- operators around the events
add("tumbling_activity", lambda s, d: ev.changes(s, d).groupBy(F.window("ts", "1 day").start.alias("day"), "source_id").agg(F.count("*").alias("events")), stack("SELECT time_bucket(INTERVAL 1 DAY, ts) AS day, source_id, count(*) AS events FROM c GROUP BY 1, 2"))
add("sliding_activity", lambda s, d: ev.changes(s, d).groupBy(F.window("ts", "2 days", "1 day").start.alias("day"), "source_id").agg(F.count("*").alias("events")), stack("SELECT time_bucket(INTERVAL 1 DAY, ts) - to_days(o) AS day, source_id, count(*) AS events FROM c, (VALUES (0), (1)) t(o) GROUP BY 1, 2"))


def _asof(s, d):
    """For each close, the last size known of the object before it: union and a running last value."""
    c = ev.changes(s, d)
    w = Window.partitionBy("source_id", "fid").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    return c.withColumn("known", F.last("size", True).over(w)).filter("op = 'CLOSE'").select("source_id", "fid", "seq", "known")


add("asof_stat", _asof, stack("SELECT source_id, fid, seq, known FROM (SELECT *, last_value(size IGNORE NULLS) OVER (PARTITION BY source_id, fid ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS known FROM c) WHERE op = 'CLOSE'"))
add("attach_stat_calls", lambda s, d: setbased.attach_stat(_lists(s, d), _after(s, d), "call").groupBy("action").agg(F.sum("stat_calls").cast("long").alias("calls")), stack(f"SELECT 'update' AS action, count(*) AS calls FROM p1 LEFT JOIN pa ON p1.source_id = pa.source_id AND p1.fid = pa.fid WHERE NOT p1.is_dir AND (pa.path IS DISTINCT FROM p1.path OR (p1.source_id, p1.fid) IN (SELECT (source_id, fid) FROM c WHERE seq > {_half})) UNION ALL SELECT 'delete', 0", **_TWO))
