"""Snapshot indexes from a stream of rows: primary records as they come, aggregate records when complete."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.monitor.notify import epochs
from fsmeta.sketch import dd
from fsmeta.snapshot import aggregate as ag
from fsmeta.snapshot import preprocess, primary


def primary_stream(raw: DataFrame, admins: tuple[str, ...] = ("group:admins",)) -> DataFrame:
    """Primary records of a stream of raw rows; narrow, no state."""
    return primary.to_records(preprocess.drop_directories(raw), admins)


class AggregateEmitter:
    """For ``foreachBatch`` on a stream of raw rows: adds up partial summaries per principal and emits each
    principal once, in the micro-batch in which its last object arrives.

    A micro-batch writes its own partial counts and buckets (``partial/epoch=N``, ``buckets/epoch=N``) and
    the records that it completes (``aggregate/epoch=N``); done again it replaces them. ``counts``: kind, id,
    n of the counting stage. Partial tables are added up, never rewritten.
    """

    def __init__(self, path: str, counts: DataFrame, low: int = 1, high: int = 5, kinds: tuple[str, ...] = ("user", "group", "dir"), qs: tuple[float, ...] = ag.QUANTILES, alpha: float = 0.01, sink: Callable[[DataFrame, int], None] | None = None):
        self.path, self.counts, self.low, self.high, self.kinds, self.qs, self.alpha, self.sink = path.rstrip("/"), counts, low, high, kinds, qs, alpha, sink

    def __call__(self, raw: DataFrame, epoch: int) -> None:
        rows = preprocess.drop_directories(raw)
        ag.totals(rows, self.low, self.high, self.kinds).write.mode("overwrite").parquet(f"{self.path}/partial/epoch={epoch}")
        ag.dd_buckets(rows, self.low, self.high, self.kinds, self.alpha).write.mode("overwrite").parquet(f"{self.path}/buckets/epoch={epoch}")
        spark = raw.sparkSession
        sums = self._sums(spark, epoch)
        done = ag.complete_principals(sums.select("kind", "id", "file_count"), self.counts).filter("complete").select("kind", "id")
        if before := [e for e in epochs(spark, f"{self.path}/aggregate") if e < epoch]:
            seen = spark.read.parquet(*[f"{self.path}/aggregate/epoch={e}" for e in before])
            done = done.join(seen.select("kind", "id"), ["kind", "id"], "left_anti")
        buckets = self._read(spark, "buckets", epoch).join(done, ["kind", "id"], "left_semi").groupBy("kind", "id", "attr", "sign", "bucket").agg(F.sum("n").alias("n"))
        q = dd.quantiles(buckets, ("kind", "id", "attr"), self.qs, self.alpha)
        out = ag.with_quantiles(sums.join(done, ["kind", "id"], "left_semi"), q, self.qs)
        out.write.mode("overwrite").parquet(f"{self.path}/aggregate/epoch={epoch}")
        if self.sink is not None:
            self.sink(spark.read.parquet(f"{self.path}/aggregate/epoch={epoch}"), epoch)

    def _read(self, spark, kind: str, epoch: int) -> DataFrame:
        return spark.read.parquet(*[f"{self.path}/{kind}/epoch={e}" for e in epochs(spark, f"{self.path}/{kind}") if e <= epoch])

    def _sums(self, spark, epoch: int) -> DataFrame:
        parts = self._read(spark, "partial", epoch)
        ends = {"min": F.min, "max": F.max, "sum": F.sum}
        return parts.groupBy("kind", "id").agg(F.sum("file_count").alias("file_count"), *[f(f"{a}_{n}").alias(f"{a}_{n}") for a in ag.ATTRIBUTES for n, f in ends.items()])

    def emitted(self, spark) -> DataFrame:
        return spark.read.parquet(*[f"{self.path}/aggregate/epoch={e}" for e in epochs(spark, f"{self.path}/aggregate")])
