"""From the two lists to ingest and delete requests, applied directly, logged, or both."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.index import store
from fsmeta.plans import workspace


def to_requests(actions: DataFrame, max_records: int = 10_000) -> DataFrame:
    """request_id, kind, source_id, batch_id, n_records, paths: one request for each list of a batch, cut at ``max_records``."""
    w = F.row_number().over(_window()) - 1
    kind = F.when(F.col("action") == "update", "ingest").otherwise("delete")
    cut = actions.withColumn("kind", kind).withColumn("piece", F.floor(w / max_records))
    out = cut.groupBy("source_id", "batch_id", "kind", "piece").agg(F.count("*").alias("n_records"), F.array_sort(F.collect_list("path")).alias("paths"))
    return out.withColumn("request_id", F.format_string("%d-%d-%s-%d", "source_id", "batch_id", "kind", "piece")).drop("piece")


def _window():
    from pyspark.sql import Window

    return Window.partitionBy("source_id", "batch_id", "action").orderBy("path", "last_seq")


def epochs(spark, path: str) -> list[int]:
    """The numbers of the finished ``epoch=N`` folders under a path."""
    mark = spark._jvm.org.apache.hadoop.fs.Path
    fs = mark(path).getFileSystem(spark._jsc.hadoopConfiguration())
    found = [s.getPath() for s in fs.listStatus(mark(path))] if fs.exists(mark(path)) else []
    return sorted(int(p.getName().split("=")[1]) for p in found if fs.exists(mark(p, "_SUCCESS")))


class Publisher:
    """For ``foreachBatch``: keeps an index and a request log under a path.

    A delivered batch writes its actions only, as rows of ``delta/epoch=N`` by bucket of the path's hash;
    the index is the newest base with the deltas after it, actions winning by sequence. A batch that is
    delivered again replaces its own delta, so nothing changes. Every ``compact_every`` epochs the base
    is written anew (deletes stay in it, for the snapshot that it is laid over), and what it covers is
    dropped, with one base kept for readers.
    """

    SCHEMA = "action string, path string, source_id long, fid long, size long, last_seq long"

    def __init__(self, path: str, target: str = "both", buckets: int = 64, compact_every: int = 32):
        if target not in ("index", "log", "both"):
            raise ValueError(target)
        self.path, self.target, self.buckets, self.compact_every = path, target, buckets, compact_every

    def __call__(self, actions: DataFrame, epoch: int) -> None:
        spark = actions.sparkSession
        if self.target in ("log", "both"):
            to_requests(actions).drop("paths").write.mode("overwrite").parquet(f"{self.path}/log/epoch={epoch}")
        if self.target in ("index", "both"):
            rows = actions.select("action", "path", "source_id", "fid", F.col("size").cast("long").alias("size"), "last_seq")
            rows = rows.withColumn("bucket", F.pmod(F.xxhash64("source_id", "path"), F.lit(self.buckets)).cast("int"))
            rows.repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/delta/epoch={epoch}")
            if epoch - self._newest(spark, "base", epoch, -1) >= self.compact_every:
                self.compact(spark, epoch)

    def compact(self, spark, epoch: int) -> None:
        """Write the index up to an epoch as a base; deltas it covers and bases before the last one go."""
        self.changes(spark, epoch).write.mode("overwrite").parquet(f"{self.path}/base/epoch={epoch}")
        old = self._newest(spark, "base", epoch - 1, -1)
        for kind, upto in (("delta", old), ("base", old - 1)):
            for e in epochs(spark, f"{self.path}/{kind}"):
                if e <= upto:
                    workspace.remove(spark, f"{self.path}/{kind}/epoch={e}")

    def _newest(self, spark, kind: str, epoch: int, none: int) -> int:
        return max((e for e in epochs(spark, f"{self.path}/{kind}") if e <= epoch), default=none)

    def changes(self, spark, epoch: int | None = None) -> DataFrame:
        """The last action of every path up to an epoch (the last one by default)."""
        epoch = (1 << 62) if epoch is None else epoch
        base = self._newest(spark, "base", epoch, -1)
        rows = spark.read.schema(self.SCHEMA).parquet(f"{self.path}/base/epoch={base}") if base >= 0 else spark.createDataFrame([], self.SCHEMA)
        if deltas := [e for e in epochs(spark, f"{self.path}/delta") if base < e <= epoch]:
            new = spark.read.option("basePath", f"{self.path}/delta").schema(self.SCHEMA + ", epoch int, bucket int").parquet(*[f"{self.path}/delta/epoch={e}" for e in deltas])
            rows = rows.unionByName(new.drop("epoch", "bucket"))
        return store.latest(rows)

    def index(self, spark, epoch: int | None = None) -> DataFrame:
        """What of that is there."""
        return self.changes(spark, epoch).filter("action <> 'delete'").select(*store.COLUMNS)
