"""One object for users: snapshots in, events in, questions out."""

from __future__ import annotations

from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fsmeta.config import PipelineConfig
from fsmeta.functions import paths
from fsmeta.index import reports, search, store
from fsmeta.monitor import ingest, notify, run
from fsmeta.plans import workspace
from fsmeta.sketch import error
from fsmeta.snapshot import aggregate, counting, preprocess, primary, versioning
from fsmeta.streaming.snapshot import AggregateEmitter


def open(spark: SparkSession, path: str, config: PipelineConfig | None = None, **settings) -> Session:  # noqa: A001
    """A session whose indexes live under ``path``. Settings override the configuration's fields."""
    return Session(spark, path, replace(config or PipelineConfig(), **settings))


class Session:
    def __init__(self, spark: SparkSession, path: str, config: PipelineConfig):
        self.spark, self.path, self.config = spark, path.rstrip("/"), config
        paths.register(spark)

    def snapshot(self, raw: DataFrame, version: int, cut: dict[int, int] | None = None) -> None:
        """Preprocess a raw snapshot and publish both indexes under a version."""
        c = self.config
        low, high = c.depth()
        rows = preprocess.drop_directories(raw)
        # counted from the source, by shard, before anything is written
        counts = counting.merge_counts(counting.shard_counts(rows, high, c.num_shards, c.kinds), low, by_shard=True)
        counts = workspace.store(counts, "counts")
        versioning.publish(rows, f"{self.path}/primary", version, cut)
        rows = self.primary()  # what has arrived
        arrived = counting.merge_counts(counting.shard_counts(rows, high, c.num_shards, c.kinds), low, by_shard=True)
        gate = workspace.store(aggregate.complete_by_shard(arrived, counts), "gate")
        agg = aggregate.aggregate(rows, low, high, c.kinds, c.quantiles, c.sketch, c.alpha, c.dir_filter)
        # a principal is published only when all its objects have arrived; the others are named
        versioning.publish(agg.join(gate.filter("complete").select("kind", "id"), ["kind", "id"], "left_semi"), f"{self.path}/aggregate", version)
        versioning.publish(gate.filter("not complete"), f"{self.path}/incomplete", version)

    def chunks(self, raw: DataFrame, align: str = "row", source: str = "source") -> str:
        """Write a raw snapshot's reduced rows as chunks of the configured size; gives their folder."""
        at = workspace.fresh(self.spark, "chunks")
        preprocess.write_chunks(preprocess.preprocess(raw), at, self.config.chunk_rows, align, source)
        return at

    def accuracy(self, algo: str | None = None) -> DataFrame:
        """Errors of the configured (or named) summarizer over users and groups with enough files."""
        c = self.config
        rows = aggregate.expand(aggregate.numbers(self.primary()), *c.depth(), ("user", "group"))
        return error.errors(rows, ("kind", "id"), aggregate.ATTRIBUTES, c.quantiles, algo or c.sketch, c.min_files)

    def incomplete(self) -> DataFrame:
        """Principals of the live version that the aggregate index lacks: kind, id, shards, missing."""
        return versioning.current(self.spark, f"{self.path}/incomplete")

    def expire(self, keep: int = 2) -> None:
        for kind in ("primary", "aggregate", "incomplete"):
            versioning.expire(self.spark, f"{self.path}/{kind}", keep)

    def stream(self, raw: DataFrame, counts: DataFrame):
        """With ``mode='stream'``: the ``foreachBatch`` function that makes aggregate records from a stream of raw rows."""
        c = self.config
        if c.mode != "stream":
            raise ValueError("set mode='stream' for a streamed snapshot")
        low, high = c.depth()
        emitter = AggregateEmitter(f"{self.path}/streamed", counts, low, high, c.kinds, c.quantiles, c.alpha)
        return raw.writeStream.foreachBatch(emitter).option("checkpointLocation", f"{self.path}/streamed/checkpoint")

    def requests(self) -> DataFrame:
        """Ingest requests of the live primary index."""
        c = self.config
        return primary.to_requests(primary.to_records(self.primary(), c.admins), c.request_bytes, c.request_wait_s, versioning.live(self.spark, f"{self.path}/primary"))

    def submit(self, send=primary.receipt) -> DataFrame:
        """Send the live version's requests and keep the log of the service's ids."""
        version = versioning.live(self.spark, f"{self.path}/primary")
        return primary.audit(primary.submit(self.requests(), send), f"{self.path}/requests", version)

    def primary(self) -> DataFrame:
        return versioning.current(self.spark, f"{self.path}/primary")

    def aggregate(self) -> DataFrame:
        return versioning.current(self.spark, f"{self.path}/aggregate")

    def monitor(self, events: DataFrame, nodes: DataFrame | None = None, feed: str = "uniform", resolver: run.Resolver | None = None) -> DataFrame:
        """Update and delete actions of a table of events; those that the live snapshot covers are passed over."""
        c = self.config
        fresh = self._after_cut(ingest.to_uniform(events, feed))
        idle = pd.Timedelta(c.idle).total_seconds()
        return run.monitor(fresh, nodes, True, c.max_events, c.drop_ops, c.max_dirs, c.stat_mode, resolver=resolver, idle_s=idle, override=c.override)

    def _after_cut(self, rows: DataFrame, seq: str = "seq") -> DataFrame:
        cut = versioning.cut(self.spark, f"{self.path}/primary")
        if not cut:
            return rows
        covered = self.spark.createDataFrame(sorted(cut.items()), "source_id long, _cut long")  # a row a source
        return rows.join(F.broadcast(covered), "source_id", "left").filter(F.col("_cut").isNull() | (F.col(seq) > F.col("_cut"))).drop("_cut")

    def _publisher(self) -> notify.Publisher:
        return notify.Publisher(f"{self.path}/changes", self.config.sink)

    def notify(self, actions: DataFrame, epoch: int) -> None:
        self._publisher()(actions, epoch)

    def index(self, snapshot: DataFrame) -> DataFrame:
        """One index from both sides: the rows of a snapshot (path, source_id, fid, size) and the published
        changes after the event sequences that it covers."""
        changes = self._after_cut(self._publisher().changes(self.spark), "last_seq")
        return store.apply(store.bootstrap(snapshot), changes)

    def search(self, filters: list[search.Match], as_user: tuple[str, ...] | None = None) -> DataFrame:
        """From the aggregate index where it can answer, else from the primary one."""
        table = self.aggregate() if search.route(filters) == "aggregate" and filters else self.primary()
        return search.search(table, filters, as_user if "uid" in table.columns else None)

    def top(self, kind: str, by: str = "size_sum", k: int = 10) -> DataFrame:
        return self.aggregate().filter(F.col("kind") == kind).select("id", by).orderBy(F.desc(by), "id").limit(k)

    def summary(self, uid: int) -> DataFrame:
        return search.summary(self.aggregate(), uid)

    def report(self, found: DataFrame, name: str, version: int) -> str:
        return reports.write_list(found, f"{self.path}/reports/{name}", version)

    def apply(self, index: DataFrame, actions: DataFrame) -> DataFrame:
        return store.apply(index, actions)
