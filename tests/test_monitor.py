"""Reduction rules case by case, equivalence of all forms, hierarchy, eviction, streams."""

import time

import pytest
from pyspark.sql import functions as F

from fsmeta.index import store
from fsmeta.monitor import batching, ingest, run, setbased
from fsmeta.monitor import reduce as rd
from fsmeta.monitor.notify import Publisher, to_requests
from fsmeta.monitor.state import CostCounters, DictStore, Event, NodeRow, StateManager, reduce_batch
from fsmeta.workloads import events as ev


def E(seq, op, fid, name=None, parent=None, size=None, is_dir=False):  # noqa: N802
    return Event(seq, op, fid, is_dir or op in ("MKDIR", "RMDIR"), parent, name, size)


CASES = [
    ("repeated updates", [E(1, "CLOSE", 5, size=1), E(2, "SETATTR", 5, size=2)], [("SETATTR", 5)]),
    ("create then unlink", [E(1, "CREATE", 5, "a", 1), E(2, "CLOSE", 5), E(3, "UNLINK", 5)], []),
    ("make then remove directory", [E(1, "MKDIR", 6, "d", 1), E(2, "RMDIR", 6)], []),
    ("unlink then create of another id", [E(1, "UNLINK", 5), E(2, "CREATE", 7, "a", 1)], [("UNLINK", 5), ("CREATE", 7)]),
    ("unlink of an older file", [E(1, "CLOSE", 5), E(2, "UNLINK", 5)], [("UNLINK", 5)]),
    ("create, rename, unlink", [E(1, "CREATE", 5, "a", 1), E(2, "RENAME", 5, "b", 1), E(3, "UNLINK", 5)], []),
    ("create and rename", [E(1, "CREATE", 5, "a", 1), E(2, "RENAME", 5, "b", 2), E(3, "CLOSE", 5, size=9)], [("CREATE", 5)]),
    ("rename and update", [E(1, "RENAME", 5, "b", 2), E(2, "CLOSE", 5, size=9)], [("RENAME", 5)]),
    ("directory rename passes all", [E(1, "CREATE", 5, "a", 1), E(2, "RENAME", 9, "n", 1, is_dir=True), E(3, "UNLINK", 5)], [("CREATE", 5), ("RENAME", 9), ("UNLINK", 5)]),
    ("directory stays", [E(1, "MKDIR", 6, "d", 1)], [("MKDIR", 6)]),
    ("nothing", [], []),
]


def frame(spark, events):
    return spark.createDataFrame([(0, 0, *e) for e in events], "source_id long, batch_id long, seq long, op string, fid long, is_dir boolean, parent_fid long, name string, size long").withColumn("ts", F.lit(None).cast("timestamp_ntz"))


@pytest.mark.parametrize("name,events,want", CASES, ids=[c[0] for c in CASES])
def test_rules(spark, name, events, want):
    assert [(e.op, e.fid) for e in reduce_batch(events, CostCounters())] == want
    got = rd.reduce(frame(spark, events)).orderBy("seq").collect()
    assert [(r["op"], r["fid"]) for r in got] == want


def test_place_and_size_survive():
    (e,) = reduce_batch([E(1, "CREATE", 5, "a", 1, 3), E(2, "RENAME", 5, "b", 2), E(3, "CLOSE", 5, size=9), E(4, "SETATTR", 5)], CostCounters())
    assert (e.op, e.parent_fid, e.name, e.size, e.seq) == ("CREATE", 2, "b", 9, 4)


def test_pairs_across_batches_survive(spark):
    b = frame(spark, [E(1, "CREATE", 5, "a", 1), E(2, "UNLINK", 5)]).withColumn("batch_id", F.col("seq"))
    assert rd.reduce(b).count() == 2


def test_reduce_identity(spark, sf):
    c = ev.changes(spark, sf)
    b = batching.assign_batches(ingest.filter_low_information(c), 50, "100000 days")
    for r in rd.reduce_stats(b, rd.reduce(b), c).collect():
        assert r["events_in"] == r["events_out"] + r["coalesced"] + r["cancelled_events"]


@pytest.mark.parametrize("batch,override", [(20, "batch"), (100, "barrier"), (1000, "batch")])
def test_all_forms_agree(spark, sf, batch, override):
    c, t = ev.changes(spark, sf), ev.changes_tree(spark, sf)
    want = setbased.index_of(setbased.resolve_paths(setbased.apply_events(t, ingest.filter_low_information(c))))
    b = batching.assign_batches(ingest.filter_low_information(c), batch, "100000 days")
    forms = [setbased.index_of(setbased.resolve_paths(setbased.apply_events(t, rd.reduce(b, override=override))))]
    empty = spark.createDataFrame([], "path string, source_id long, fid long, size long, last_seq long")
    for reduce in (True, False):
        a = run.monitor(c, t, reduce, batch)
        once = store.apply(empty, a)
        forms.append(once.select("source_id", "fid", "path", "size"))
        assert store.apply(once, a).exceptAll(once).count() == 0
    for f in forms:
        assert f.exceptAll(want.select(f.columns)).count() == 0 and want.select(f.columns).exceptAll(f).count() == 0


def manager(**options):
    m = StateManager(**options)
    for fid, parent, name in ((-1, None, "s"), (10, -1, "a"), (11, 10, "b"), (12, -1, "c")):
        m.load(fid, NodeRow(parent, name, True, None, None))
    return m


def run_one(m, events, reduce=True):
    return [(a.action, a.fid, a.path) for a in m.process(events, reduce)]


def test_hierarchy():
    m = manager()
    assert run_one(m, [E(1, "CREATE", 5, "f", 11, 7)]) == [("update", 5, "/s/a/b/f")]
    assert run_one(m, [E(2, "RENAME", 10, "z", -1, is_dir=True)]) == [("delete", 5, "/s/a/b/f"), ("update", 5, "/s/z/b/f")]
    assert run_one(m, [E(3, "RENAME", 11, "b2", 12, is_dir=True)]) == [("delete", 5, "/s/z/b/f"), ("update", 5, "/s/c/b2/f")]
    assert run_one(m, [E(4, "RENAME", 5, "g", 10)]) == [("delete", 5, "/s/c/b2/f"), ("update", 5, "/s/z/g")]
    assert run_one(m, [E(5, "RENAME", 10, "y", -1, is_dir=True), E(6, "UNLINK", 5)]) == [("delete", 5, "/s/z/g"), ("delete", 5, "/s/y/g")]
    assert run_one(m, [E(7, "MKDIR", 20, "n", 12), E(8, "CREATE", 21, "h", 20)]) == [("update", 21, "/s/c/n/h")]


def test_resolver_is_asked_once():
    asked = []

    def resolve(fid):
        asked.append(fid)
        return NodeRow(None, "root", True, None, None) if fid == 99 else None

    m = StateManager(resolver=resolve)
    for i in range(5):
        run_one(m, [E(i, "CREATE", 100 + i, f"f{i}", 99)])
    assert asked == [99] and m.counters.lookups == 1 and m.path(103) == "/root/f3"


def test_eviction_keeps_active_paths():
    everything = {i: NodeRow(-1, f"d{i}", True, None, None) for i in range(50)} | {-1: NodeRow(None, "s", True, None, None)}
    m = StateManager(resolver=everything.get, max_dirs=5)
    for turn in range(3):
        for i in range(50):
            fid = 1000 + turn * 50 + i
            assert run_one(m, [E(fid, "CREATE", fid, f"f{fid}", i)]) == [("update", fid, f"/s/d{i}/f{fid}")]
            assert run_one(m, [E(fid + 5000, "UNLINK", fid)]) == [("delete", fid, f"/s/d{i}/f{fid}")]
    assert m.counters.evicted > 0 and len(m.recent) <= 7


def test_workloads_cancel(spark, sf):
    for make, batch in ((ev.mixed_ops, 700), (ev.create_delete, 300)):
        e = make(spark, sf, 2)
        assert run.monitor(e, ev.roots(e), True, batch).count() == 0
        assert run.monitor(e, ev.roots(e), True, batch + 1).count() > 0
    e = ev.tree_read(spark, sf, 1)
    c = run.costs(e, ev.read_tree(spark, sf, 1), True, 1000).first()
    assert c["opens_dropped"] * 2 == c["events_in"] and c["updates"] > 0


def test_requests(spark):
    a = spark.createDataFrame([("update", 0, i, f"/p{i}", 1, i, 0) for i in range(25)] + [("delete", 0, 99, "/q", None, 30, 0)], run.ACTIONS)
    got = to_requests(a, 10).collect()
    assert sorted((r["kind"], r["n_records"]) for r in got) == [("delete", 1), ("ingest", 5), ("ingest", 10), ("ingest", 10)]


def test_stream_equals_batch(spark, sf, tmp_path):
    from fsmeta.streaming import monitor as sm

    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    c, t = ev.changes(spark, sf), ev.changes_tree(spark, sf)
    want = setbased.index_of(setbased.resolve_paths(setbased.apply_events(t, ingest.filter_low_information(c))))
    nodes = t.select("source_id", F.lit(-1).cast("long").alias("seq"), F.lit(None).cast("timestamp").alias("ts"), F.lit("NODE").alias("op"), "fid", "is_dir", "parent_fid", "name", "size")
    nodes.coalesce(1).write.parquet(f"{tmp_path}/in")
    pub = Publisher(f"{tmp_path}/out")

    def go():
        q = sm.actions_stream(sm.read_events(spark, f"{tmp_path}/in"), 50).writeStream.foreachBatch(pub).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
        q.awaitTermination(120)
        assert not q.isActive and q.exception() is None

    half = c.agg(F.max("seq") / 2).first()[0]
    for part in ("seq <= {h}", "seq > {h}"):  # stopped in between, and goes on from the checkpoint
        time.sleep(1.1)
        c.filter(part.format(h=half)).withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        go()
    got = pub.index(spark).select(want.columns)
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0
    assert spark.read.parquet(f"{tmp_path}/out/log").count() > 0
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)


def test_changelog_stream(spark, sf, tmp_path):
    from fsmeta.sources import feeds

    lines = ingest.render_changelog(ev.changes(spark, sf)).collect()
    for r in lines:
        with open(tmp_path / f"{r['source_id']}.log", "a") as f:
            f.write(r["line"] + "\n")
    s = ingest.parse_changelog(feeds.read_changelog(spark, str(tmp_path)))
    q = s.writeStream.format("memory").queryName("feed").trigger(availableNow=True).start()
    q.awaitTermination(60)
    assert spark.table("feed").count() == len(lines)
    reader = feeds.ChangelogReader({"path": str(tmp_path)})
    end = reader.latestOffset()
    reader.commit(end)
    assert (tmp_path / "cleared.json").exists() and reader.partitions(end, end) == [] and len(reader.partitions({}, end)) == 5


def test_windows_and_duplicates_in_a_stream(spark, sf, tmp_path):
    from fsmeta.streaming import monitor as sm

    c = ev.changes(spark, sf).withColumn("ts", F.col("ts").cast("timestamp"))
    c.union(c.limit(20)).coalesce(1).write.parquet(f"{tmp_path}/in")
    for name, df in (("tumble", sm.activity(sm.unique(sm.read_events(spark, f"{tmp_path}/in"), "1000 days"), late="1000 days")), ("once", sm.unique(sm.read_events(spark, f"{tmp_path}/in"), "1000 days"))):
        q = df.writeStream.format("memory").queryName(name).outputMode("complete" if name == "tumble" else "append").trigger(availableNow=True).start() if name == "once" else None
        if q:
            q.awaitTermination(60)
            assert spark.table(name).count() == c.count()
    assert isinstance(DictStore().children(1), list)


def test_batches_by_stretches(spark):
    """A large source in many pieces, uneven numbers, a small source beside it: batches are those of the whole order."""
    rows = [(s, i * i if i % 3 else i * i * i, "CREATE", i) for s, n in ((1, 400), (None, 30), (2, 5)) for i in range(n)]
    e = spark.createDataFrame(rows, "source_id long, seq long, op string, fid long").withColumn("ts", F.timestamp_seconds(F.lit(0)).cast("timestamp_ntz"))
    want = {}
    for s in (1, None, 2):
        order = sorted({(q, f) for x, q, _, f in rows if x == s}, key=lambda x: x[0])
        want |= {(s, f): (i, q) for i, (q, f) in enumerate(order)}
    got = batching.assign_batches(e, 7, "100000 days", stretch=16).collect()
    assert len(got) == len(rows)
    # numbers that two events share may come either way
    ties = {(s, q): [want[s, f][0] // 7 for x, q2, _, f in rows if (x, q2) == (s, q)] for s, q, _, _ in rows}
    assert all(r["batch_id"] in ties[r["source_id"], r["seq"]] for r in got)
    sizes = [n for s in (1, None, 2) for n in sorted(r["count"] for r in batching.assign_batches(e, 7, "100000 days", stretch=16).groupBy("source_id", "batch_id").count().filter(F.col("source_id").eqNullSafe(F.lit(s))).collect())]
    assert sizes == [1] + [7] * 57 + [2] + [7] * 4 + [5]


@pytest.mark.parametrize("stretch", [50, batching.STRETCH])
def test_batches_and_their_counts_from_one_pass(spark, sf, stretch):
    for c in (ev.changes(spark, sf), ev.mixed_ops(spark, sf, 2)):
        c = ingest.filter_low_information(c)
        whole = batching.assign_batches(c, 30, "100000 days")
        b = batching.assign_batches(c, 30, "100000 days", stretch=stretch)
        assert b.columns == whole.columns and b.schema["batch_id"].dataType == whole.schema["batch_id"].dataType
        key = ("source_id", "seq", "batch_id")
        assert b.select(*key).exceptAll(whole.select(*key)).isEmpty() and b.count() == whole.count()
        stats, want = rd.batch_stats(b), rd.reduce_stats(b, rd.reduce(b))
        assert stats.select(want.columns).exceptAll(want).isEmpty() and stats.count() == want.count()
        assert {r["source_id"]: r["batches"] for r in stats.collect()} == {r["source_id"]: r["n"] for r in b.groupBy("source_id").agg(F.countDistinct("batch_id").alias("n")).collect()}


def test_pauses_still_end_batches(spark):
    e = spark.range(100).selectExpr("1L AS source_id", "id AS seq", "CAST(timestamp_seconds(id + id div 10 * 60) AS timestamp_ntz) AS ts")
    assert sorted(r["count"] for r in batching.assign_batches(e, 7, "5 seconds", stretch=16).groupBy("batch_id").count().collect()) == [3] * 10 + [7] * 10
