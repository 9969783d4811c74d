"""Batches of events per source: closed at a number of events or after a pause."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


STRETCH = 1 << 18  # events of a source that one task orders


def assign_batches(events: DataFrame, max_events: int = 1000, idle: str = "5 seconds", stretch: int = STRETCH) -> DataFrame:
    """Adds batch_id. Order within a source is total. Where its times allow no pause, a large source is ordered in
    stretches of sequence numbers, of which each knows how many events are before it; else a source is sorted as one."""
    span = events.groupBy("source_id").agg(F.count("*").alias("n"), F.min("seq").alias("first"), F.max("seq").alias("last"), F.coalesce(F.max("ts") - F.min("ts") > F.expr(f"INTERVAL {idle}"), F.lit(False)).alias("pauses"))
    # a row for each ``stretch`` events at most
    big = F.when((F.col("n") > stretch) & F.col("first").isNotNull(), F.struct("source_id", "n", "first", "last"))
    found = span.agg(F.max("pauses").alias("pauses"), F.collect_list(big).alias("large")).first()
    if found["large"] and not found["pauses"]:
        return _by_stretches(events, max_events, found["large"], stretch)
    w = Window.partitionBy("source_id").orderBy("seq")
    pause = F.col("ts") - F.lag("ts").over(w) > F.expr(f"INTERVAL {idle}")
    e = events.withColumn("_new", F.coalesce(pause, F.lit(False)).cast("int"))
    e = e.withColumn("_session", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    s = Window.partitionBy("source_id", "_session").orderBy("seq")
    e = e.withColumn("_chunk", F.floor((F.row_number().over(s) - 1) / max_events))
    b = Window.partitionBy("source_id").orderBy("_session", "_chunk")
    return e.withColumn("batch_id", F.dense_rank().over(b).cast("long") - 1).drop("_new", "_session", "_chunk")


def _by_stretches(events: DataFrame, max_events: int, large: list, stretch: int) -> DataFrame:
    spark = events.sparkSession
    widths = [(r["source_id"], r["first"], max(1, -(-(r["last"] - r["first"] + 1) * stretch // r["n"]))) for r in large]
    kind = events.schema["source_id"].dataType.simpleString()
    e = events.join(F.broadcast(spark.createDataFrame(widths, f"source_id {kind}, _first long, _width long")), "source_id", "left")
    e = e.withColumn("_at", F.coalesce(F.expr("(seq - _first) div _width"), F.lit(0).cast("long"))).drop("_first", "_width")
    base, done = [], {}
    # of the large sources, about a row for each ``stretch`` events
    for source, at, n in sorted(e.join(F.broadcast(spark.createDataFrame([(x[0],) for x in widths], f"source_id {kind}")), "source_id").groupBy("source_id", "_at").count().collect()):
        base.append((source, at, done.get(source, 0)))
        done[source] = done.get(source, 0) + n
    e = e.join(F.broadcast(spark.createDataFrame(base, f"source_id {kind}, _at long, _base long")), ["source_id", "_at"], "left")
    row = F.row_number().over(Window.partitionBy("source_id", "_at").orderBy("seq")) - 1
    return e.withColumn("batch_id", F.expr("coalesce(_base, 0L)") + row).withColumn("batch_id", F.floor(F.col("batch_id") / max_events).cast("long")).select(*events.columns, "batch_id")
