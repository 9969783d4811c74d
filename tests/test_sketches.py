"""Summarizers and error measures on small vectors and against exact ranks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from fsmeta.sketch import base, dd, error
from fsmeta.sketch.exact import exact, exact_selected, exact_spilling
from fsmeta.sketch.req import Req
from fsmeta.sketch.tdigest import TDigest

QS = (0.1, 0.25, 0.5, 0.75, 0.9, 0.99)


@pytest.fixture(scope="module")
def df(spark):
    rng = np.random.default_rng(1)
    rows = [("a", float(v)) for v in rng.lognormal(8, 2, 3000)] + [("b", 5.0)] + [("c", 0.0)] * 9 + [("d", float(v)) for v in rng.normal(0, 50, 500)] + [("e", None)]
    return spark.createDataFrame(rows, "g string, v double").repartition(5)


@pytest.mark.parametrize("algo", ["exact", "dd", "kll", "req", "tdigest", "gk"])
def test_quantiles(df, algo):
    got = {r["g"]: r["q"] for r in base.quantiles(df, ("g",), ("v",), QS, algo).collect()}
    assert set(got) == {"a", "b", "c", "d"}
    assert got["c"] == [0.0] * 6 and all(abs(x - 5) <= 0.05 for x in got["b"])
    for k, q in got.items():
        assert q == sorted(q), (algo, k)
    a = np.sort([r["v"] for r in df.filter("g = 'a'").collect()])
    for q, e in zip(QS, got["a"], strict=True):
        if algo == "dd":
            assert abs(e - a[int(q * (len(a) - 1))]) <= 0.0101 * e
        else:
            assert abs(np.searchsorted(a, e) / len(a) - q) < 0.04, (algo, q)


def test_dd_merge_and_collapse(df):
    b = dd.buckets(df, ("g",), ("v",), 0.01)
    halves = dd.buckets(df.filter("v > 100"), ("g",), ("v",), 0.01).unionByName(dd.buckets(df.filter("v <= 100"), ("g",), ("v",), 0.01))
    assert dd.merge(halves, ("g", "attr")).exceptAll(b.select("g", "attr", "sign", "bucket", "n")).count() == 0
    small = dd.collapse(b, ("g", "attr"), 250)
    assert small.groupBy("g").count().agg(F.max("count")).first()[0] <= 250
    assert small.groupBy("g").agg(F.sum("n").alias("n")).exceptAll(b.groupBy("g").agg(F.sum("n").alias("n"))).count() == 0
    top = {r["g"]: r["q"] for r in dd.quantiles(small, ("g", "attr"), (0.99,)).collect()}
    full = {r["g"]: r["q"] for r in dd.quantiles(b, ("g", "attr"), (0.99,)).collect()}
    assert top["a"] == full["a"]


def test_exact_forms_agree(df):
    a = {(r["g"], i): v for r in exact(df, ("g",), ("v",), QS).collect() for i, v in enumerate(r["q"])}
    for form in (exact_spilling, exact_selected):
        b = {(r["g"], i): v for r in form(df, ("g",), ("v",), QS).collect() for i, v in enumerate(r["q"])}
        assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-6 for k in a)


def test_errors_by_hand(spark):
    d = spark.createDataFrame([("x", v) for v in (1.0, 1.0, 1.0, 1.0, 10.0)] + [("z", 0.0)], "g string, v double")
    truth = exact(d, ("g",), ("v",), (0.5,))
    est = truth.withColumn("q", F.when(F.col("g") == "x", F.array(F.lit(2.0))).otherwise(F.array(F.lit(3.0))))
    v = {r["g"]: r["value_error"] for r in error.value_error(truth, est, ("g", "attr"), (0.5,)).collect()}
    assert v["x"] == 1.0 and v["z"] is None
    r = {t: error.rank_error(d.filter("g = 'x'"), est, ("g",), ("v",), (0.5,), t).first()["rank_error"] for t in ("left", "right", "closest")}
    assert r == {"left": pytest.approx(0.3), "right": pytest.approx(0.3), "closest": pytest.approx(0.3)}
    same = {t: error.rank_error(d.filter("g = 'x'"), truth, ("g",), ("v",), (0.5,), t).first()["rank_error"] for t in ("left", "right", "closest")}
    assert same == {"left": pytest.approx(0.5), "right": pytest.approx(0.3), "closest": 0.0}


def test_trade_off_on_times(spark):
    """Values close together relative to their size: the value sketch keeps value error low, rank sketches keep rank error low."""
    rng = np.random.default_rng(3)
    d = spark.createDataFrame([("g", float(v)) for v in rng.uniform(9.0e8, 1.0e9, 4000)], "g string, v double")
    e = {a: error.errors(d, ("g",), ("v",), QS, a).first() for a in ("dd", "kll", "req", "tdigest")}
    assert e["dd"]["value_error_max"] < 0.01
    assert all(e[a]["rank_error_max"] < e["dd"]["rank_error_max"] for a in ("kll", "req", "tdigest"))


@pytest.mark.parametrize("kind", [Req, TDigest])
def test_numpy_sketches_merge(kind):
    rng = np.random.default_rng(4)
    parts = [rng.exponential(10, 5000) for _ in range(8)]
    s = kind()
    for p in parts:
        o = kind()
        o.add(p)
        s.merge(kind.load(o.dump()))
    every = np.sort(np.concatenate(parts))
    weight = s.weight.sum() if kind is TDigest else s.items()[1].sum()
    assert weight == len(every)
    for q, v in zip(QS, s.quantiles(QS), strict=True):
        assert abs(np.searchsorted(every, v) / len(every) - q) < 0.03
    assert kind is TDigest or len(s.dump()) < 40_000


@pytest.mark.parametrize("kind", ["req", "tdigest"])
def test_small_groups_are_not_cut_up(spark, kind):
    """More groups than a task holds sketches of, each met again and again: one row for each, and nothing lost."""
    groups, times = 25_000, 10
    d = spark.range(groups * times, numPartitions=1).selectExpr(f"id % {groups} AS g", "CAST(id AS DOUBLE) AS v")
    parts = base.partial(d, ("g",), ("v",), kind)
    assert parts.agg(F.count("*"), F.sum("n"), F.min("n"), F.max("high")).first()[:] == (groups, groups * times, times, groups * times - 1.0)
    got = base.quantiles(d, ("g",), ("v",), (0.0, 1.0), kind).agg(F.count("*"), F.count_if(F.get("q", 0) == F.col("g")), F.count_if(F.get("q", 1) == F.col("g") + groups * (times - 1))).first()
    assert got[:] == (groups,) * 3


def test_estimates_of_small_groups_do_not_hang_on_partitions(spark):
    rng = np.random.default_rng(7)
    rows = [(g, float(v), None if v > 1.5 else float(-v)) for g in range(3) for v in rng.lognormal(0, 1, 70 * (g + 1))] + [(None, 1.0, None)]
    d = spark.createDataFrame(rows, "g long, v double, w double")
    for kind in ("req", "tdigest"):
        one, more = (sorted(((r["g"], r["attr"], r["q"]) for r in base.quantiles(d.repartition(n), ("g",), ("v", "w"), QS, kind).collect()), key=repr) for n in (1, 7))
        assert one == more and len(one) == 7


def test_large_groups_come_as_sketches_among_small_ones(spark):
    d = spark.range(12_000, numPartitions=3).selectExpr("CASE WHEN id % 3 = 0 THEN id ELSE -1 END AS g", "CAST(id AS DOUBLE) AS v", "CASE WHEN id % 2 = 0 THEN CAST(-id AS DOUBLE) END AS w")
    for kind in ("req", "tdigest"):
        parts = base.partial(d, ("g",), ("v", "w"), kind, held=1, buffered=1000, block=1000)
        assert {(r["g"] == -1, r["plain"]) for r in parts.select("g", "plain").distinct().collect()} == {(True, False), (False, True)}
        est = base.quantiles(d, ("g",), ("v", "w"), QS, kind, held=1, buffered=1000, block=1000)
        e = error.rank_error(d, est, ("g",), ("v", "w"), QS)
        assert e.count() == 6 * (4_001 + 2_001) and e.filter("g = -1 AND rank_error > 0.05").isEmpty()
