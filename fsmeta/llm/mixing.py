"""Mixing sources to target weights by a low-discrepancy schedule of equal-word blocks.

1. Targets: a total of ``share`` times all words, split by weight; a source's target stops at
   ``cap`` times its words and the excess is dealt again by weight (water filling, worked out
   with running sums over the sources ordered by where they saturate).
2. Blocks: within a source the documents are laid end to end in an order shuffled by hash and
   cut into blocks of ``block`` words. Positions come from two-level running sums, so no
   source is ever gathered in one task.
3. Schedule: slot k takes the golden-ratio point of k (integers modulo 2^31). The rank of a slot's
   point among all points, mapped through the cumulative slot quotas, is its source: every source
   gets exactly its quota, and any prefix of the slots holds the sources in nearly the same shares.
   The rank of the slot within its source names the block (wrapping round for further epochs);
   a source's last slot is cut to its target.
4. Blocks joined with slots are the mix: word ranges of documents by slot (``mixed``). What a
   document gives to the slots, and when first, is added up from them (``mix``).

Defined results: null text has no words; null sources form one source, the last by order;
empty documents take nothing; repeated rows are mixed each on its own (equal rows may swap
places, which changes nothing); no words at all give targets of 0. Reruns agree, as all
order comes from hashes of the rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fsmeta.llm.common import WORD
from fsmeta.plans import workspace

#: Modulus of the points, and the odd number nearest to the golden ratio of it.
MODULUS, STEP = 1 << 31, 1_327_217_885
#: Documents and slots that a bucket of the two-level running sums has on average.
BUCKET_ROWS, ROWS_A_BUCKET = 2_000, 1 << 14


def cycle_weights(rank: Column, weights: tuple[float, ...] = (3.0, 1.0, 2.0)) -> Column:
    return F.element_at(F.array(*map(F.lit, weights)), (rank % len(weights) + 1).cast("int"))


def targets(sizes: DataFrame, weight=cycle_weights, share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """One row a source: sid, source, rows, source_size, weight, target. ``sizes``: source, size."""
    s = sizes.groupBy("source").agg(F.count("*").alias("rows"), F.sum("size").alias("source_size"))
    s = s.withColumn("sid", F.row_number().over(Window.orderBy(F.col("source").isNull(), "source")) - 1)
    s = s.withColumn("weight", weight(F.col("sid"))).withColumn("most", cap * F.col("source_size"))
    everything = Window.partitionBy()
    filling = Window.orderBy(F.col("most") / F.col("weight"), "sid").rowsBetween(Window.unboundedPreceding, -1)
    zero = F.lit(0.0)
    left = share * F.sum("source_size").over(everything) - F.coalesce(F.sum("most").over(filling), zero)
    weights = F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(filling), zero)
    s = s.withColumn("level", left / weights)
    s = s.withColumn("open", F.when(F.col("level") * F.col("weight") < F.col("most"), F.struct((F.col("most") / F.col("weight")).alias("a"), "sid", "level")))
    final = F.min("open").over(everything)["level"]
    return s.withColumn("target", F.least(F.coalesce(final * F.col("weight"), F.col("most")), F.col("most"))).select("sid", "source", "rows", "source_size", "weight", "target")


def plan(sources: DataFrame, block: int) -> DataFrame:
    """Blocks, epochs and slot quota of each source, and its range [lo, hi) of the points' ranks."""
    size, want = F.col("source_size"), F.round("target").cast("long")
    s = sources.filter(F.col("source_size") > 0).withColumn("want", want).withColumn("blocks", F.ceil(size / block).cast("long"))
    s = s.withColumn("rest", F.col("want") % size).withColumn("quota", (F.floor(F.col("want") / size) * F.col("blocks") + F.ceil(F.col("rest") / block)).cast("long"))
    s = s.withColumn("tail", F.when(F.col("rest") == 0, F.lit(block)).otherwise((F.col("rest") - 1) % block + 1).cast("long"))
    s = s.withColumn("hi", F.sum("quota").over(Window.orderBy("sid").rowsBetween(Window.unboundedPreceding, 0)))
    return s.withColumn("lo", F.col("hi") - F.col("quota")).filter(F.col("quota") > 0)


def schedule(planned: DataFrame) -> DataFrame:
    """One row a slot: slot (its place in the mix), sid, rank within the source, block, words at most."""
    spark = planned.sparkSession
    n = planned.agg(F.coalesce(F.sum("quota"), F.lit(0)).cast("long")).first()[0]  # one number
    cell = max(1, n >> 14)  # slots a cell, and as many ranks
    points = spark.range(n).withColumnRenamed("id", "slot").withColumn("point", F.col("slot") % MODULUS * STEP % MODULUS)
    # points are spread evenly: buckets of like size that rise with them
    ranked = running(points.withColumns({"one": F.lit(1), "all": F.lit(0)}), "all", F.floor(F.col("point") / max(1, MODULUS // max(1, n // ROWS_A_BUCKET))), ["point", "slot"], "one")
    ranked = ranked.select("slot", F.col("before").alias("at")).withColumn("cell", F.floor(F.col("at") / cell))
    cells = planned.select("sid", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / cell), F.floor((F.col("hi") - 1) / cell))).alias("cell"))
    dealt = ranked.join(cells, (ranked.cell == cells.cell) & (F.col("at") >= F.col("lo")) & (F.col("at") < F.col("hi"))).select("slot", "sid")
    slots = running(dealt.withColumn("one", F.lit(1)), "sid", F.floor(F.col("slot") / ROWS_A_BUCKET), ["slot"], "one").select("slot", "sid", F.col("before").alias("rank"))
    slots = slots.join(planned.select("sid", "quota", "blocks", "tail"), "sid")
    return slots.select("slot", "sid", "rank", (F.col("rank") % F.col("blocks")).alias("block"), F.when(F.col("rank") == F.col("quota") - 1, F.col("tail")).alias("cut"))


def running(rows: DataFrame, key: str, bucket: Column, order: list, value: str) -> DataFrame:
    """``before``: sum of ``value`` over the rows of the same key that come earlier.

    ``bucket`` must rise with ``order``. Sums of buckets are run up first, then each bucket
    on its own: a hot key is spread over its buckets.
    """
    rows = rows.withColumn("_bucket", bucket)
    sums = rows.groupBy(key, "_bucket").agg(F.sum(value).alias("_sum"))
    up = Window.partitionBy(key).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(key, "_bucket", F.coalesce(F.sum("_sum").over(up), F.lit(0)).alias("_base"))
    own = Window.partitionBy(key, "_bucket").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return rows.join(sums, [key, "_bucket"]).withColumn("before", F.col("_base") + F.coalesce(F.sum(value).over(own), F.lit(0))).drop("_bucket", "_base")


def placed(docs: DataFrame, key: str, text: str, source: str, weight, share: float, cap: float) -> tuple[DataFrame, DataFrame]:
    """(rows: doc_id, size, source_size, target, sid, before (words of the source ahead), rid; the sources)."""
    sized = docs.select(docs[key].alias("doc_id"), docs[source].cast("string").alias("source"), F.coalesce(F.regexp_count(docs[text], F.lit(WORD)), F.lit(0)).cast("long").alias("size"), F.xxhash64(docs[key], docs[text]).alias("h"))
    sized = workspace.store(sized, "sizes")
    sources = workspace.store(targets(sized, weight, share, cap), "sources")
    named = sources.withColumnRenamed("source", "_s")
    rows = sized.join(named, sized.source.eqNullSafe(F.col("_s"))).drop("_s")
    parts = F.ceil(F.col("rows") / BUCKET_ROWS)
    rows = running(rows, "sid", F.least(F.floor((F.col("h") / 2.0**64 + 0.5) * parts), parts - 1), ["h", "doc_id", "size"], "size")
    rows = rows.select("doc_id", "size", "source_size", "target", "sid", "before", F.monotonically_increasing_id().alias("rid"))
    return workspace.store(rows, "places"), sources


def taken_parts(rows: DataFrame, sources: DataFrame, block: int) -> DataFrame:
    """slot, rid, lo, hi: the words [lo, hi) of a row that a slot of the mix holds."""
    first, last = F.floor(F.col("before") / block), F.floor((F.col("before") + F.col("size") - 1) / block)
    parts = rows.filter("size > 0").withColumn("block", F.explode(F.sequence(first, last)))
    ahead = F.col("block") * block - F.col("before")  # words of the row ahead of the block's start
    parts = parts.select("rid", "sid", "block", ahead.alias("ahead"), F.greatest(F.lit(0), ahead).alias("lo"), F.least("size", ahead + block).alias("hi"))
    got = parts.join(schedule(plan(sources, block)), ["sid", "block"])
    return got.select("slot", "rid", "lo", F.least("hi", F.col("ahead") + F.coalesce("cut", F.lit(block))).alias("hi")).filter("hi > lo")


def mixed(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weight=cycle_weights, share: float = 1.5, cap: float = 2.0, block: int = 128) -> DataFrame:
    """The mix itself: slot, doc_id, and the words [lo, hi) of the document that stand there."""
    rows, sources = placed(docs, key, text, source, weight, share, cap)
    return taken_parts(rows, sources, block).join(rows.select("rid", "doc_id"), "rid").select("slot", "doc_id", "lo", "hi")


def mix(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weight=cycle_weights, share: float = 1.5, cap: float = 2.0, block: int = 128) -> DataFrame:
    """doc_id, size, source_size, target, taken, first_slot (null if none) and n_slots of each row."""
    rows, sources = placed(docs, key, text, source, weight, share, cap)
    sums = taken_parts(rows, sources, block).groupBy("rid").agg(F.sum(F.col("hi") - F.col("lo")).cast("long").alias("taken"), F.min("slot").alias("first_slot"), F.count("*").alias("n_slots"))
    zero = F.lit(0).cast("long")
    return rows.join(sums, "rid", "left").select("doc_id", "size", "source_size", "target", F.coalesce("taken", zero).alias("taken"), "first_slot", F.coalesce("n_slots", zero).alias("n_slots"))
