"""One registered query for each operator of this folder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fsmeta.llm.common import crc_mod, table


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm import language_id

    docs = table(spark, sf_dir, "documents")
    out = F.coalesce(crc_mod(F.col("doc_id"), 4) == 2, F.lit(False))
    model = language_id.fit(docs, ~out)
    return language_id.identify(docs, model).select("doc_id", out.alias("held_out"), "lang_pred", "score", "rejected")


def op2_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.html_text import extract

    return extract(table(spark, sf_dir, "pages"))


def op3_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.token_output import store_tokens

    return store_tokens(table(spark, sf_dir, "documents"), tokenizer="byte_bpe_50k.json", end_id=2)


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.decontamination import leaks

    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), budget=0.1)


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.mixing import mix

    return mix(table(spark, sf_dir, "documents"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.quality_rules import judge

    good = table(spark, sf_dir, "labels").filter("quality = 1").select("doc_id")
    return judge(table(spark, sf_dir, "documents"), good)


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.jaccard_join import join_components

    return join_components(table(spark, sf_dir, "documents"), span=5, percent=75)


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.token_counts import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), tokenizer="word_bpe_49k.json", limit=2048)


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm.suffix_dedup import remove_repeats

    return remove_repeats(table(spark, sf_dir, "documents"), length=200)


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from fsmeta.llm import quality_classifier as qc

    docs = table(spark, sf_dir, "documents")
    model = qc.fit(docs, table(spark, sf_dir, "labels"), crc_mod(F.col("k"), 5) != 0)
    out = qc.score(docs, model, keep=("doc_id",))
    return out.select("doc_id", F.coalesce(crc_mod(F.col("doc_id"), 5) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_language_id, op2_html_extraction, op3_token_output, op4_decontamination, op5_mixing, op6_quality_rules, op7_jaccard_join, op8_token_counts, op9_suffix_dedup, op10_quality_classifier)}


def oracle_sql() -> dict[str, str]:
    return {}
