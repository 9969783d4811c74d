"""Quality rules with DataFrame functions only: countable base rules, then a hashed n-gram
log-likelihood ratio between a trusted target and the raw corpus.

Tokens are runs of letters and digits or runs of other signs, lower-cased; unigrams and
bigrams are hashed into ``buckets``. The raw multinomial counts every document; the target
multinomial counts the trusted ones. A document's score is the sum of the log ratios of its
n-grams divided by their number; it is kept if the score is at least ``threshold`` (fixed, no
randomness). The table of log ratios has exactly ``buckets`` entries.

Defined results: null text has no words; a text without n-grams scores 0; without trusted
documents all ratios are 0; texts of under ten words always fail the base rules; repeated rows
give repeated rows; extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fsmeta.llm.common import WORD, let, words

TOKENS = "[\\p{L}\\p{M}\\p{N}]+|[^\\p{L}\\p{M}\\p{N}\\x20\\x09-\\x0D]+"
SYMBOLS = "[#*$%&|<>]"
#: Trusted keys (8 bytes each) that are broadcast at most; more are joined by a shuffle.
LISTED = 2_000_000


def repeated_words(w: Column, span: int = 5) -> Column:
    """Words inside windows of ``span`` words that occur more than once in the array ``w``.

    Windows are compared by a 64-bit hash of their words' hashes. Texts whose windows all
    differ stop after one hash set; the others sort (hash, start) pairs, look at neighbours,
    and add up the covered stretches from start to start.
    """

    def windows(h):
        return F.transform(F.sequence(F.lit(0), F.size(h) - span), lambda i: F.xxhash64(*[F.get(h, i + j) for j in range(span)]))

    def covered(starts):
        gaps = F.zip_with(starts, F.slice(starts, 2, F.size(starts)), lambda a, b: F.coalesce(F.least(b - a, F.lit(span)), F.lit(span)))
        return F.aggregate(gaps, F.lit(0), lambda s, g: s + g)

    def twins(pairs):
        near = F.zip_with(pairs, F.concat(F.slice(pairs, 1, 1), pairs), lambda a, b: F.struct(a["h"].alias("h"), a["i"].alias("i"), b["h"].alias("p")))
        # ``near`` has one element more than there are pairs (the last has no window of its own)
        near = F.slice(near, 1, F.size(pairs))
        marked = F.zip_with(near, F.slice(near, 2, F.size(pairs)), lambda a, b: F.struct(a["i"].alias("i"), a["h"].alias("h"), a["p"].alias("p"), b["h"].alias("n")))
        first = F.element_at(pairs, 1)["i"]
        own = F.filter(marked, lambda x: F.coalesce(x["h"] == x["n"], F.lit(False)) | ((x["h"] == x["p"]) & (x["i"] != first)))
        return let(F.array_sort(F.transform(own, lambda x: x["i"])), covered)

    def count(wh):
        pairs = F.sort_array(F.transform(wh, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(wh)) == F.size(wh), F.lit(0)).otherwise(let(pairs, twins))

    hashes = F.transform(w, lambda x: F.xxhash64(x))
    return F.when(F.size(w) > span, let(let(hashes, windows), count)).otherwise(F.lit(0)).cast("long")


def base(docs: DataFrame, key: str = "doc_id", text: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """Base counts and base_failed for each row."""
    t = F.coalesce(docs[text], F.lit(""))
    d = docs.select(docs[key], *keep, t.alias("_t")).withColumn("_w", words(F.col("_t")))
    lines = F.filter(F.split("_t", "\n"), lambda x: x.rlike(WORD))
    repeats = let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x)))
    d = d.select(
        key,
        *keep,
        F.size("_w").cast("long").alias("n_words"),
        F.char_length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        F.regexp_count("_t", F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
        repeats.cast("long").alias("n_dup_lines"),
        repeated_words(F.col("_w")).alias("n_repeat_words"),
        "_t",
    )
    return d.withColumn("base_failed", (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")))


def grams(text: Column, buckets: int) -> Column:
    """Buckets of the hashed unigrams and bigrams of a text."""
    hashed = F.transform(F.regexp_extract_all(F.lower(text), F.lit(TOKENS), F.lit(0)), lambda w: F.xxhash64(w))

    def both(h):
        pairs = F.zip_with(h, F.slice(h, 2, F.greatest(F.size(h), F.lit(1))), lambda a, b: F.pmod(F.xxhash64(a, b, F.lit(2)), F.lit(buckets)).cast("int"))
        return F.concat(F.transform(h, lambda a: F.pmod(a, F.lit(buckets)).cast("int")), pairs)

    return let(hashed, both)


def log_ratios(docs: DataFrame, trusted: DataFrame, key: str = "doc_id", text: str = "text", buckets: int = 1 << 14, listed: int = LISTED) -> DataFrame:
    """bucket, lr for every bucket. All documents give the raw multinomial, those with a
    ``trusted`` key the target one."""
    ids = trusted.select(F.col(trusted.columns[0]).alias("k")).filter("k is not null").distinct().withColumn("good", F.lit(1))
    every = docs.select(docs[key].alias("k"), F.coalesce(docs[text], F.lit("")).alias("t"))
    if ids.count() <= listed:
        marked = every.join(F.broadcast(ids), "k", "left")
    else:
        # null keys match nothing and would all meet in one task; texts are not sorted
        keyed = every.filter("k is not null").join(ids.hint("shuffle_hash"), "k", "left")
        marked = keyed.unionByName(every.filter("k is null").withColumn("good", F.lit(None).cast("int")))
    seen = marked.select("good", F.explode(grams(F.col("t"), buckets)).alias("bucket"))
    n = seen.groupBy("bucket").agg(F.count("*").alias("raw"), F.count("good").alias("target"))
    every = docs.sparkSession.range(buckets).select(F.col("id").cast("int").alias("bucket"))
    n = every.join(n, "bucket", "left").select("bucket", F.coalesce("raw", F.lit(0)).alias("raw"), F.coalesce("target", F.lit(0)).alias("target"))
    total = Window.partitionBy()
    lr = F.log((F.col("target") + 1) / (F.sum("target").over(total) + buckets)) - F.log((F.col("raw") + 1) / (F.sum("raw").over(total) + buckets))
    return n.select("bucket", F.when(F.sum("target").over(total) > 0, lr).otherwise(F.lit(0.0)).alias("lr"))


def judge(docs: DataFrame, trusted: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = -0.3, buckets: int = 1 << 14, **options) -> DataFrame:
    """Base counts, base_failed, llr and kept for each row."""
    # ``buckets`` numbers, a fixed bound, become one constant of the plan
    ratios = log_ratios(docs, trusted, key, text, buckets, **options).orderBy("bucket").toPandas()["lr"]
    lrs = F.split(F.lit(",".join(map(repr, ratios.tolist()))), ",").cast("array<double>")
    d = base(docs, key, text)
    score = let(grams(F.col("_t"), buckets), lambda g: F.aggregate(g, F.lit(0.0), lambda s, b: s + F.get(lrs, b)) / F.greatest(F.size(g), F.lit(1)))
    d = d.withColumn("llr", score).drop("_t")
    return d.withColumn("kept", ~F.col("base_failed") & (F.col("llr") >= threshold))
