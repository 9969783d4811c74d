"""Preprocessing, primary records, counting, versions, search and sources."""

import json
import zlib

import pytest
from pyspark.sql import functions as F

from fsmeta import fixtures as fx
from fsmeta.config import PipelineConfig
from fsmeta.functions import paths
from fsmeta.index import search as q
from fsmeta.plans import workspace
from fsmeta.snapshot import aggregate as ag
from fsmeta.snapshot import counting as ct
from fsmeta.snapshot import preprocess as pp
from fsmeta.snapshot import primary as pr
from fsmeta.snapshot import versioning as vs
from fsmeta.sources import dump, listing


def test_escape_round_trip(spark):
    odd = ["/a,b", "/a\nb", "/a\tb", '/"q"', "/back\\slash", "/\\n", "/\\b\\", "/ü/#?", "/\\\\c,", ""]
    df = spark.createDataFrame([(o,) for o in odd], "path string").select("path", paths.escape_path(F.col("path")).alias("e"))
    got = df.select("path", "e", paths.unescape_path(F.col("e")).alias("b")).collect()
    assert all(r["path"] == r["b"] and not set(r["e"]) & set(',\n\t\r"#?') for r in got)
    paths.register(spark)
    r = spark.sql("SELECT unescape_path(escape_path('/a,b\\\\n')) AS p, dd_bucket(100D, 0.01D) AS b").first()
    assert r["p"] == "/a,b\\n" and r["b"] == 231
    assert [tuple(r) for r in spark.sql("SELECT * FROM path_prefixes('/a/b/c.txt', 1, 5)").collect()] == [(1, "/a"), (2, "/a/b")]


def test_mode_text(spark):
    df = spark.createDataFrame([("f", 100644, "-rw-r--r--"), ("l", 120777, "lrwxrwxrwx"), ("f", 104755, "-rwsr-xr-x"), ("f", 102644, "-rw-r-Sr--"), ("f", 101777, "-rwxrwxrwt"), ("d", 41776, "drwxrwxrwT"), ("f", 100000, "----------")], "t string, m int, w string")
    assert df.filter(paths.mode_text(F.col("t"), F.col("m")) != F.col("w")).count() == 0


def test_chunks(spark, sf):
    df = fx.fs_large(spark, sf).select("path", "size", F.col("uid").alias("source"))
    at = workspace.fresh(spark, "chunks")
    pp.write_chunks(df, at, 1000)
    n = spark.read.schema("path string, size long, source long").csv(at).withColumn("f", F.input_file_name()).groupBy("f").count()
    assert n.agg(F.max("count")).first()[0] <= 1000 and n.agg(F.sum("count")).first()[0] == df.count()
    at = workspace.fresh(spark, "chunks")
    pp.write_chunks(df, at, 1500, align="source")
    back = spark.read.csv(at).select(F.col("_c2").alias("source"), "chunk")
    assert back.groupBy("source").agg(F.countDistinct("chunk").alias("n")).filter("n > 1").count() == 0 and back.count() == df.count()


def test_requests(spark, sf):
    records = pr.to_records(fx.fs_large(spark, sf)).repartition(3)
    sent = pr.to_requests(records, max_bytes=100_000)
    rows = sent.collect()
    assert all(len(r["payload"].encode()) == r["n_bytes"] <= 100_000 for r in rows)
    subjects = [json.loads(line)["subject"] for r in rows for line in r["payload"].split("\n")]
    assert sorted(subjects) == sorted(r["subject"] for r in records.select("subject").collect())
    assert len({r["request_id"] for r in rows}) == len(rows)
    tiny = pr.to_requests(records.limit(5), max_bytes=10).collect()
    assert [r["n_records"] for r in tiny] == [1] * 5
    plan = records._jdf.queryExecution().optimizedPlan().toString()
    assert "Aggregate" not in plan


def test_shards_match_zlib(spark):
    df = spark.createDataFrame([("/a/ü.txt", "f", 100644, 1, 2, 3, "x", "y", "z")], "path string, type string, mode int, uid long, gid long, size long, atime string, ctime string, mtime string")
    got = df.select(ct.shard_id(64).alias("s")).first()["s"]
    assert got == zlib.crc32("/a/ü.txt,f,100644,1,2,3,x,y,z".encode()) % 64


@pytest.mark.parametrize("shards,parts", [(1, 2), (7, 5), (64, 1)])
def test_counts_do_not_depend_on_shards(spark, sf, shards, parts):
    want = ct.merge_counts(ct.shard_counts(fx.fs_large(spark, sf), 4, 16))
    got = ct.merge_counts(ct.shard_counts(fx.fs_large(spark, sf).repartition(parts), 4, shards))
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0
    assert ct.recursive_counts(ct.shard_counts(fx.fs_large(spark, sf), 4, shards)).filter("id = '/'").first()["n"] == 6000


def test_publish_twice(spark, sf):
    at = workspace.fresh(spark, "versions")
    a, b = fx.versions(spark, sf)
    assert vs.live(spark, at) is None
    for _ in range(2):
        vs.publish(a, at, 1)
    assert vs.current(spark, at).count() == a.count()
    vs.publish(b, at, 2, {0: 17})
    assert vs.live(spark, at) == 2 and vs.current(spark, at).count() == b.count()
    b = b.dropDuplicates(["path"])
    assert vs.diff(b, b).count() == 0


def test_aggregate_options(spark, sf):
    large = fx.fs_large(spark, sf)
    some = ag.aggregate(large, 3, 4, ("dir",), dir_filter="/fs/r1")
    assert {r["id"].count("/") for r in some.select("id").collect()} == {3, 4} and some.filter(~F.col("id").startswith("/fs/r1")).count() == 0
    more = ag.aggregate(large, 1, 2, ("user",), qs=(0.5, 0.999))
    assert "size_p99_9" in more.columns
    for algo in ("exact", "kll", "tdigest"):
        assert ag.aggregate(large, 1, 1, ("group",), sketch=algo).count() == large.select("gid").distinct().count()
    assert PipelineConfig(depth_base="/fs/r1", depth_levels=1).depth() == (2, 3)


def test_search(spark, sf):
    p = fx.fs_large(spark, sf)
    total = p.count()
    for m, n in (
        (q.Match("type", "eq", "l"), p.filter("type = 'l'").count()), (q.Match("type", "ne", "l"), p.filter("type <> 'l'").count()), (q.Match("size", "between", (1, 10**12)), total), (q.Match("uid", "in", (1, 2)), p.filter("uid in (1, 2)").count()),
        (q.Match("checksum", "null"), total), (q.Match("checksum", "null", False), 0), (q.Match("path", "prefix", "/fs/r1/"), p.filter("path like '/fs/r1/%'").count()), (q.Match("uid", "regex", "^1$"), p.filter("uid = 1").count()),
    ):
        assert q.search(p, [m]).count() == n, m
    assert q.route([q.Match("size_sum", "gt", 1)]) == "aggregate" and q.route([q.Match("path", "eq", "x")]) == "primary"
    assert q.search(p, [], ("group:admins",)).count() == total and q.visible(p, ("user:nobody",)).count() == 0
    with pytest.raises(ValueError):
        q.Match("a", "no").column()


def test_dump_source(spark, tmp_path):
    rows = {f"/home/u{i}/d{j}": [(f"f{k}", "f", 100644, i, 1, 10 * k, 1, 2, 3) for k in range(5)] + [("sub", "d", 40755, i, 1, 4096, 1, 2, 3)] for i in range(3) for j in range(4)}
    dump.write_dump(rows, str(tmp_path))
    dump.register(spark)
    df = spark.read.format("fsdump").option("packBytes", 20_000).load(str(tmp_path))
    assert df.rdd.getNumPartitions() > 1 and df.count() == 72
    assert df.filter("size > 20 and type = 'f'").count() == 24
    assert df.filter("path = '/home/u1/d2' and uid = 1").count() == 6
    assert pp.drop_directories(df).count() == 60


def test_listing_source(spark, sf):
    at = workspace.fresh(spark, "listing")
    raw = fx.fs_medium_raw(spark, sf)
    listing.write_listing(raw, at)
    back = listing.read_listing(spark, at)
    assert len(back.columns) == 18
    cols = ["path", "type", "mode", "uid", "gid", "size", "atime", "fileset"]
    assert back.select(cols).exceptAll(raw.select(cols)).count() == 0 and back.count() == raw.count()
    scan = pp.preprocess(back)._jdf.queryExecution().executedPlan().toString()
    assert "generation" not in scan.split("ReadSchema")[-1]


def test_plans(spark, sf):
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    dd = text(ag.dd_buckets(fx.fs_small(spark, sf), 1, 3))
    assert "Python" not in dd and "Arrow" not in dd
    counts = text(ct.shard_counts(fx.fs_small(spark, sf), 3))
    assert counts.count("documents.parquet") <= 1
    cold = text(q.past_retention(spark.read.parquet(f"{sf}/lineitem.parquet").withColumnRenamed("l_shipdate", "mtime").withColumnRenamed("l_returnflag", "path"), "1996-01-01"))
    assert "PushedFilters: [IsNotNull(l_shipdate)" in cold
