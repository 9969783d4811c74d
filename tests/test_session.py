"""The user-facing object from snapshot to report."""

from fsmeta import fixtures as fx
from fsmeta import session
from fsmeta.index.search import Match
from fsmeta.plans import workspace
from fsmeta.workloads import events as ev
from fsmeta.workloads import stages


def test_session(spark, sf):
    s = session.open(spark, workspace.fresh(spark, "session"), directory_max=4, sink="both", max_events=100)
    s.snapshot(fx.fs_medium_raw(spark, sf), 1, {0: 5})
    assert s.primary().count() == 1500 and s.aggregate().filter("kind = 'group'").count() == 25
    assert s.requests().agg({"n_records": "sum"}).first()[0] == 1500
    assert s.search([Match("kind", "eq", "user"), Match("file_count", "gt", 0)]).count() == s.primary().select("uid").distinct().count()
    assert s.search([Match("type", "eq", "f")], ("user:1",)).filter("uid <> 1").count() == 0
    assert s.top("user", k=3).count() == 3 and s.summary(1).count() == 1
    at = s.report(s.search([Match("size", "gt", 10)]).select("path"), "big", 1)
    lines = [r[0] for r in spark.read.option("header", True).csv(at).collect()]
    assert len(lines) == 1500
    assert s.incomplete().count() == 0
    assert s.spark.read.csv(s.chunks(fx.fs_medium_raw(spark, sf))).count() == 1500
    s.notify(s.monitor(ev.changes(spark, sf), ev.changes_tree(spark, sf)), 0)


def test_lost_rows_are_told(spark, sf, monkeypatch):
    from fsmeta.snapshot import versioning

    whole, publish = fx.fs_medium_raw(spark, sf), versioning.publish
    monkeypatch.setattr(versioning, "publish", lambda df, path, *a: publish(df.filter("uid <> 7") if path.endswith("/primary") else df, path, *a))
    s = session.open(spark, workspace.fresh(spark, "lossy"), directory_max=4)
    s.snapshot(whole, 1)
    lost = {(r["kind"], r["id"]) for r in s.incomplete().collect()}
    assert ("user", "7") in lost and not any(k == "user" and i != "7" for k, i in lost)
    assert s.aggregate().filter("kind = 'user' AND id = '7'").count() == 0 and s.aggregate().filter("kind = 'user'").count() > 0


def test_accuracy_of_the_session(spark, sf):
    s = session.open(spark, workspace.fresh(spark, "accuracy"), directory_max=4, min_files=10)
    s.snapshot(fx.fs_medium_raw(spark, sf), 1)
    assert s.accuracy().first()["value_error_max"] < 0.1


def test_stage_sweep(spark, sf):
    rows = stages.chunked(spark, fx.fs_medium(spark, sf), 400)
    assert len(rows.inputFiles()) >= 4 and rows.count() == 1500
    assert set(stages.run_stages(rows, 1, 4)) == {"primary", "counting", "aggregate"}
