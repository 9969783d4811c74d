"""Corpus pipeline: classify, deduplicate, decontaminate, mix, write token ids.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes every stage's
result as Parquet in the shared folder and reads it again for the next one. All stages but
the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fsmeta.llm import decontamination, jaccard_join, mixing, quality_classifier, token_output
from fsmeta.llm.common import crc_mod, table
from fsmeta.plans import workspace

#: Keys (8 bytes each) that a stage broadcasts at most; more are joined by a shuffle.
LISTED = 2_000_000


def without(docs: DataFrame, keys: DataFrame) -> DataFrame:
    """Rows whose doc_id is not among ``keys`` (distinct, one column). Null keys stay."""
    keys = workspace.store(keys, "dropped")
    return docs.join(F.broadcast(keys) if keys.count() <= LISTED else keys, "doc_id", "left_anti").select(docs.columns)


def classify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose quality score is at least 0.3."""
    model = quality_classifier.fit(docs, table(spark, sf_dir, "labels"), crc_mod(F.col("k"), 5) != 0)
    scored = quality_classifier.score(docs, model, name="_quality_score")
    return scored.filter(F.col("_quality_score") >= 0.3).select(docs.columns)


def deduplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group, that of the least doc_id. Texts without words and rows
    without a key stay, but of rows equal in key and text one does; an empty table stays empty."""
    member = workspace.store(jaccard_join.join_components(docs), "members")
    sizes = member.agg(F.count("doc_id").alias("n"), F.countDistinct("doc_id").alias("d")).first()
    kept = without(docs, member.filter(F.col("doc_id") != F.col("component_id")).select("doc_id").distinct())
    # keys that repeat: rows that are equal are copies too
    return kept if sizes["n"] == sizes["d"] else kept.dropDuplicates(["doc_id", "text"])


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item. Null texts hold none; rows without a key stay, as they can't be named."""
    found = decontamination.leaks(docs, table(spark, sf_dir, "benchmark"))
    return without(docs, found.select("doc_id").distinct())


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes their words, rounded to whole documents. Null and empty texts have
    no words and are not taken; rows equal in key, text and source share what they are taken; an empty table stays empty."""
    # a hash passes nulls over: what is null counts too
    parts = ("doc_id", "text", "source")
    keyed = docs.withColumn("_row_key", F.xxhash64(*parts, *[F.col(c).isNull() for c in parts]))
    mixed = mixing.mix(keyed, key="_row_key")
    copies = mixed.groupBy("doc_id").agg(F.sum("taken").alias("taken"), F.sum("size").alias("size"))
    copies = copies.select(F.col("doc_id").alias("_row_key"), F.round(F.col("taken") / F.greatest("size", F.lit(1))).cast("int").alias("_copies")).filter("_copies > 0")
    again = keyed.join(copies, "_row_key").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies"))))
    return again.select(docs.columns)


def write_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, read back from the id files. Null texts are the end
    id alone; rows without a key come first; repeated rows are all written; an empty table gives no rows."""
    return token_output.store_tokens(docs, cache_entries=300_000)


STAGES = [
    ("quality_classifier", classify),
    ("jaccard_join", deduplicate),
    ("decontamination", decontaminate),
    ("mixing", mix),
    ("token_output", write_ids),
]

#: SQL can't express the classifier's fit, the alignment or the tokenizer; tests/llm holds the brute-force comparison.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        before, docs = docs, workspace.store(stage(spark, docs, sf_dir), name)
        workspace.drop(before)  # only what a stage wrote
    out = STAGES[-1][1](spark, docs, sf_dir)  # reads the id files, which are written by now
    workspace.drop(docs)
    return out
