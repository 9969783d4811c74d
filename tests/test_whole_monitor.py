"""Events, files and versions that must not get lost."""

import sqlite3
import time

import pytest
from pyspark.sql import functions as F

from fsmeta.index import store
from fsmeta.monitor import baseline, run
from fsmeta.monitor.notify import Publisher
from fsmeta.monitor.state import CostCounters, Event, NodeRow, Spilled, StateManager, reduce_batch
from fsmeta.snapshot import versioning as vs
from fsmeta.workloads import events as ev


def E(seq, op, fid, name=None, parent=None, size=None, is_dir=False):  # noqa: N802
    return Event(seq, op, fid, is_dir or op in ("MKDIR", "RMDIR"), parent, name, size)


def run_one(m, events, reduce=True):
    return [(a.action, a.fid, a.path) for a in m.process(events, reduce)]


def test_unresolved_events_are_counted_and_wait():
    m = StateManager()
    assert run_one(m, [E(1, "CREATE", 5, "f", 50, 3), E(2, "MKDIR", 51, "d", 50), E(3, "CREATE", 6, "g", 51)]) == []
    assert m.counters.unresolved == 2
    m.load(-1, NodeRow(None, "s", True, None, None))
    assert run_one(m, [E(4, "MKDIR", 50, "late", -1)]) == [("update", 5, "/s/late/f"), ("update", 6, "/s/late/d/g")]
    assert run_one(m, [E(5, "UNLINK", 999)]) == [] and m.counters.unresolved == 3


def test_eviction_takes_files_along_and_brings_them_back():
    out = Spilled()
    m = StateManager(resolver=out.get, spill=out.put, below=out.children, max_dirs=2)
    m.load(-1, NodeRow(None, "s", True, None, None))
    for i in range(60):
        assert run_one(m, [E(10 * i, "MKDIR", 100 + i, f"d{i}", -1), E(10 * i + 1, "CREATE", 1000 + i, f"f{i}", 100 + i)]) == [("update", 1000 + i, f"/s/d{i}/f{i}")]
    assert len(m.recent) <= 3 and m.counters.evicted >= 57 and len(m.store.nodes) < 10
    assert run_one(m, [E(900, "CLOSE", 1003, size=4)]) == [("update", 1003, "/s/d3/f3")]
    # a rename reaches what was evicted below
    assert run_one(m, [E(901, "RENAME", 107, "z", -1, is_dir=True)]) == [("delete", 1007, "/s/d7/f7"), ("update", 1007, "/s/z/f7")]
    assert run_one(m, [E(902, "UNLINK", 1009)]) == [("delete", 1009, "/s/d9/f9")]


def test_pluggable_rules_and_barrier():
    pair = (("RENAME", "UNLINK"),)
    got = reduce_batch([E(1, "RENAME", 5, "b", 1), E(2, "UNLINK", 5), E(3, "CREATE", 6, "a", 1), E(4, "UNLINK", 6)], CostCounters(), pair)
    assert [(e.op, e.fid) for e in got] == [("UNLINK", 6)]
    batch = [E(1, "CREATE", 5, "a", 1), E(2, "UNLINK", 5), E(3, "RENAME", 9, "n", 1, is_dir=True), E(4, "CLOSE", 7), E(5, "CLOSE", 7)]
    assert [e.seq for e in reduce_batch(batch, CostCounters())] == [1, 2, 3, 4, 5]
    assert [e.seq for e in reduce_batch(batch, CostCounters(), override="barrier")] == [3, 5]


def test_idle_limit_closes_batches(spark):
    rows = [(0, 1, "2024-01-01 00:00:00", "CREATE", 5, False, -1, "a", 1), (0, 2, "2024-01-01 00:00:01", "CLOSE", 5, False, None, None, 2), (0, 3, "2024-01-01 00:01:00", "UNLINK", 5, False, None, None, None)]
    e = spark.createDataFrame(rows, "source_id long, seq long, ts string, op string, fid long, is_dir boolean, parent_fid long, name string, size long").withColumn("ts", F.col("ts").cast("timestamp"))
    assert run.monitor(e, ev.roots(e)).count() == 0
    got = [(r["action"], r["batch_id"]) for r in run.monitor(e, ev.roots(e), idle_s=5.0).collect()]
    assert got == [("update", 0), ("delete", 1)]


def test_lookup_baseline_gives_the_same_lists(spark, sf):
    e = ev.create_delete(spark, sf, 2).filter("seq < 400")
    roots = ev.roots(e)
    a = baseline.lookup_pipeline(e, roots, wait_s=0.0, drop=("OPEN",)).drop("batch_id")
    b = run.monitor(e, roots, False, 1).drop("batch_id")
    assert a.count() == b.count() > 0 and a.exceptAll(b).count() == 0


def test_table_resolver_is_bounded(spark, sf):
    with pytest.raises(ValueError):
        run.table_resolver(ev.changes_tree(spark, sf), 3)


def test_publisher_writes_deltas_and_compacts(spark, tmp_path):
    p, want = Publisher(f"{tmp_path}/p", "index", buckets=4, compact_every=3), spark.createDataFrame([], "path string, source_id long, fid long, size long, last_seq long")
    for epoch in range(8):
        a = spark.createDataFrame([("update", 0, i, f"/f{i}", 1, 10 * epoch + 1, 0) for i in range(epoch, epoch + 3)] + [("delete", 0, epoch - 1, f"/f{epoch - 1}", None, 10 * epoch + 2, 0)], run.ACTIONS)
        p(a, epoch)
        p(a, epoch)  # delivered again
        want = store.apply(want, a)
        now = p.index(spark)
        assert now.exceptAll(want.select(now.columns)).count() == 0 and want.count() == now.count()
    kept = {f.name for f in (tmp_path / "p" / "delta").iterdir()}
    assert len(kept) < 8 and len(list((tmp_path / "p" / "base").iterdir())) <= 2


def test_versions_expire(spark, tmp_path):
    at = f"{tmp_path}/v"
    assert vs.expire(spark, at) == [] and vs.cut(spark, at) == {}
    for v in (1, 2, 3, 4):
        vs.publish(spark.range(v), at, v, {0: 10 * v})
    assert vs.cut(spark, at) == {0: 40} and vs.expire(spark, at, 2) == [1, 2]
    assert vs.live(spark, at) == 4 and vs.current(spark, at).count() == 4
    assert not (tmp_path / "v" / "data" / "version=1").exists() and (tmp_path / "v" / "data" / "version=3").exists()


def test_dump_keeps_dots_of_names(spark, tmp_path):
    from fsmeta.sources import dump

    row = ("f", "f", 100644, 1, 1, 5, 0, 0, 0)
    dump.write_dump({"/.cache/x": [row], "/a/..b": [row], "/": [row]}, str(tmp_path))
    dump.register(spark)
    got = {r["path"] for r in spark.read.format("fsdump").load(str(tmp_path)).collect()}
    assert got == {"/.cache/x", "/a/..b", "/"}
    sqlite3.connect(":memory:").close()


def test_feed_offsets_stand_after_whole_lines(tmp_path):
    from fsmeta.sources import feeds

    f = tmp_path / "3.log"
    f.write_bytes("one\ntwo \x0c name\u2028x\nhalf".encode())
    r = feeds.ChangelogReader({"path": str(tmp_path)})
    end = r.latestOffset()
    (part,) = r.partitions({}, end)
    assert list(r.read(part)) == [(3, "one"), (3, "two \x0c name\u2028x")]
    with open(f, "ab") as g:
        g.write(b" line\n")
    (part,) = r.partitions(end, r.latestOffset())
    assert list(r.read(part)) == [(3, "half line")]
    r.commit(r.latestOffset())
    assert feeds.ChangelogReader({"path": str(tmp_path)}).initialOffset() == r.latestOffset()


def test_stream_batches_reach_over_micro_batches(spark, tmp_path):
    from fsmeta.streaming import monitor as sm

    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    rows = [[(0, -1, None, "NODE", -1, True, None, "s", None), (0, 1, 0, "CREATE", 5, False, -1, "a", 1), (0, 2, 1, "CREATE", 6, False, -1, "b", 1)], [(0, 3, 2, "UNLINK", 5, False, None, None, None), (0, 4, 900, "CLOSE", 6, False, None, None, 7)]]
    for i, part in enumerate(rows):
        df = spark.createDataFrame(part, "source_id long, seq long, at long, op string, fid long, is_dir boolean, parent_fid long, name string, size long")
        df.withColumn("ts", F.timestamp_seconds("at")).drop("at").select("source_id", "seq", "ts", "op", "fid", "is_dir", "parent_fid", "name", "size").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        got = []
        q = sm.actions_stream(sm.read_events(spark, f"{tmp_path}/in"), idle_ms=600_000).writeStream.foreachBatch(lambda d, e: got.extend(d.collect())).option("checkpointLocation", f"{tmp_path}/cp").start()
        until = time.time() + 60
        while time.time() < until and sum(p["numInputRows"] for p in q.recentProgress) < len(part):
            time.sleep(0.3)
        q.stop()
        assert q.exception() is None
        if i == 0:
            assert got == []  # the batch is still open
    # 5 came and went in one batch, though in two micro-batches; the pause closed it
    assert [(r["action"], r["fid"], r["path"]) for r in got] == [("update", 6, "/s/b")]
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)


def test_streamed_aggregates(spark, sf, tmp_path):
    from fsmeta import fixtures as fx
    from fsmeta.snapshot import aggregate as ag
    from fsmeta.snapshot import counting as ct
    from fsmeta.streaming import snapshot as ss

    rows = fx.fs_medium(spark, sf)
    for i in range(3):
        rows.filter(F.col("uid") % 3 == i).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    counts = ct.merge_counts(ct.shard_counts(rows, 3))
    e = ss.AggregateEmitter(f"{tmp_path}/out", counts, 1, 3)
    s = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    assert ss.primary_stream(s).isStreaming
    q = s.writeStream.foreachBatch(e).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination(150)
    assert q.exception() is None
    want = ag.aggregate(rows, 1, 3)
    r = [F.round(c, 6).alias(c) if c not in ("kind", "id", "file_count") else F.col(c) for c in want.columns]
    got = e.emitted(spark).select(*want.columns)
    assert got.count() == want.count() and got.select(*r).exceptAll(want.select(*r)).count() == 0
    # some were complete before the last micro-batch
    assert spark.read.parquet(f"{tmp_path}/out/aggregate/epoch=0").count() > 0


def test_shard_ids_are_those_of_zlib(spark, sf):
    import zlib

    from fsmeta import fixtures as fx
    from fsmeta.snapshot import counting as ct

    cols = ("path", "type", "uid", "gid", "size")
    for r in fx.fs_medium(spark, sf).select(*cols, ct.shard_id(16, cols).alias("shard")).limit(200).collect():
        assert r["shard"] == zlib.crc32(",".join(str(r[c]) for c in cols).encode()) % 16


def test_look_ups_forget_no_living_id(spark, sf):
    """More living ids than any fixed number of entries: each is asked for once, however long it is not seen."""
    n = 1_000_100
    e = spark.range(2 * n, numPartitions=4).selectExpr("CAST(0 AS BIGINT) AS source_id", "id AS seq", "'OPEN' AS op", f"id % {n} AS fid")
    (r,) = baseline.per_event_lookup(e).collect()
    assert (r["events"], r["calls"], r["hits"]) == (2 * n, n, n)


def test_look_ups_with_and_without_bound_agree(spark, sf):
    c = ev.changes(spark, sf)
    kept, bounded, few = (sorted(map(tuple, baseline.per_event_lookup(c, n).collect())) for n in (None, 10**6, 3))
    assert kept == bounded and all(a[2] < b[2] for a, b in zip(kept, few, strict=True))
    odd = spark.createDataFrame([(1, 1, "CREATE", 5), (1, 2, None, 5), (1, 3, "UNLINK", 5), (1, 4, "OPEN", 5), (1, 5, "OPEN", None), (1, 6, "CLOSE", None)], "source_id long, seq long, op string, fid long")
    for n in (None, 10):
        assert [(r["events"], r["calls"], r["hits"]) for r in baseline.per_event_lookup(odd, n).collect()] == [(6, 3, 3)]
