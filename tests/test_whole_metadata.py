"""Nothing of the job is left out: baselines with files, evicted directories, all principals."""


import pytest

from fsmeta.monitor import run, setbased
from fsmeta.monitor.state import NodeRow, StateManager

NODES = [(1, 1, None, "s", True, None), (1, 2, 1, "a", True, None), (1, 5, 2, "f", False, 7), (1, 6, 2, "g", False, 8), (1, 7, 1, "h", False, 9)]


def nodes_of(spark):
    return spark.createDataFrame(NODES, "source_id long, fid long, parent_fid long, name string, is_dir boolean, size long")


def events_of(spark, rows):
    return spark.createDataFrame([(1, *r) for r in rows], "source_id long, seq long, op string, fid long, is_dir boolean, parent_fid long, name string, size long")


def test_files_of_the_baseline_move_and_go(spark):
    e = events_of(spark, [(1, "UNLINK", 7, False, None, None, None), (2, "RENAME", 6, False, 1, "k", None), (3, "RENAME", 2, True, 1, "b", None)])
    n = nodes_of(spark)
    want = setbased.actions(setbased.resolve_paths(n), setbased.resolve_paths(setbased.apply_events(n, e)))
    pick = lambda df: sorted((r["action"], r["fid"], r["path"], r["size"]) for r in df.collect())
    got = pick(run.monitor(e, n, True, 100))
    assert got == pick(want) == [("delete", 5, "/s/a/f", None), ("delete", 6, "/s/a/g", None), ("delete", 7, "/s/h", None), ("update", 5, "/s/b/f", 7), ("update", 6, "/s/k", 8)]


def test_accuracy_is_swept_over_users_and_groups(spark, sf, monkeypatch):
    from fsmeta import catalog_snapshot as cs

    seen = []

    def errors(df, by, *_):
        seen.append(df.select(*by).distinct())
        return df.limit(0)

    monkeypatch.setattr(cs.error, "errors", errors)
    cs.R["accuracy_fs_small"][0](spark, sf)
    n = cs.ag.numbers(cs.fx.SNAPSHOTS["fs_small"](spark, sf))
    users, groups = (n.select(c).distinct().count() for c in ("uid", "gid"))
    assert {r["kind"]: r["count"] for r in seen[0].groupBy("kind").count().collect()} == {"user": users, "group": groups}


def test_evicted_and_unknown_directories_come_back(spark):
    made = [(s, "MKDIR", 100 + s, True, 1, f"d{s}", None) for s in range(20)] + [(30, "RENAME", 100, True, 2, "moved", None)]
    late = [(40 + s, "CREATE", 200 + s, False, 100 + s, f"f{s}", 1) for s in range(20)]
    e, n = events_of(spark, made + late), nodes_of(spark)
    pick = lambda df: sorted((r["action"], r["fid"], r["path"]) for r in df.collect())
    got = pick(run.monitor(e, n, True, 1, max_dirs=3))
    assert len(got) == 20 and got == pick(run.monitor(e, n, True, 1)) and got[0][2] == "/s/a/moved/f0"
    below = [(s, "SETATTR", 100 + s, True, None, None, None) for s in range(3)] + [(9, "CREATE", 201, False, 2, "x", 1)]
    known = {f: NodeRow(p, name, d, None, size) for _, f, p, name, d, size in NODES}
    assert pick(run.monitor(events_of(spark, below), None, True, 1, resolver=lambda _, fid: known.get(fid))) == [("update", 201, "/s/a/x")]


def test_limits_need_a_resolver():
    from fsmeta.streaming.monitor import MetadataStateProcessor

    for make in (lambda: StateManager(max_dirs=3), lambda: MetadataStateProcessor(ttl_ms=1000)):
        with pytest.raises(ValueError):
            make()


def test_requests_are_tried_again_and_refusals_are_logged(spark, sf, tmp_path):
    from fsmeta import fixtures as fx
    from fsmeta.snapshot import primary as pr

    marks = str(tmp_path)

    def send(payload):
        import os
        import zlib

        mark = f"{marks}/{zlib.crc32(payload.encode())}"
        if not os.path.exists(mark):
            open(mark, "w").close()
            raise OSError("busy")
        return "ok"

    def never(payload):
        raise OSError("down")

    requests = pr.to_requests(pr.to_records(fx.fs_medium(spark, sf)), max_bytes=100_000).cache()
    log = pr.audit(pr.submit(requests, send), f"{tmp_path}/log", 1).collect()
    assert len(log) == requests.count() > 1 and {(r["task_id"], r["tries"]) for r in log} == {("ok", 2)}
    assert {(r["task_id"], r["tries"]) for r in pr.submit(requests, never, 2).collect()} == {(None, 2)}
    requests.unpersist()
