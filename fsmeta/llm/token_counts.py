"""Token counts by a two-tier look-up, without any shuffle of pre-tokens.

Every task counts its pre-tokens and passes on only a bounded summary of the most frequent;
the summaries give a table of at most ``table_size`` pre-token lengths, which is broadcast.
A pre-token that is not in it is encoded by the library once per worker and kept in a bounded
cache. The counts are those of the library whatever the table holds.

Defined results: null text is an empty text (0 tokens); the special strings of the
vocabulary inside a text count as the library takes them; repeated rows give repeated rows.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.llm import pretokens
from fsmeta.llm.common import lean
from fsmeta.llm.token_output import slices


def _library(tok, items: list[str]) -> list[int]:
    """Tokens of each pre-token, many in a call."""
    out: list[int] = []
    for at in range(0, len(items), 4096):
        part = items[at : at + 4096]
        words = tok.encode(part, is_pretokenized=True, add_special_tokens=False).word_ids
        out += np.bincount(np.array(words, np.int64), minlength=len(part)).tolist()
    return out


class Tiers(dict):
    """The frequent table first; what it lacks comes from the worker's cache or the text's own new pre-tokens."""

    def __init__(self, frequent: dict, cache: dict, new: dict):
        super().__init__(frequent)
        self.cache, self.new = cache, new

    def __missing__(self, t: str) -> int:
        n = self.cache.get(t)
        return self.new[t] if n is None else n


def frequent_lengths(docs: DataFrame, tokenizer: str, text: str = "text", table_size: int = 32_768, per_task: int = 4_096, held: int = 200_000) -> dict[str, int]:
    """Lengths of the most frequent pre-tokens of the whole corpus, at most ``table_size``.

    A task holds at most ``held`` counters; beyond that the rarest are let go. What reaches
    the driver is bounded by ``table_size``.
    """

    def summary(batches):
        seen: Counter = Counter()
        special = None
        for b in lean(batches):
            special = special if special is not None else pretokens.specials(pretokens.load(tokenizer))
            for t in b.column(0).to_pylist():
                if t and pretokens.plain(t, special):
                    seen.update(pretokens.WORD_END.findall(t.lower()))
            if len(seen) > held:
                seen = Counter(dict(seen.most_common(held // 2)))
        top = [(t, n) for t, n in seen.most_common(per_task) if len(t) <= 40]
        if top:
            yield pa.RecordBatch.from_arrays([pa.array([t for t, _ in top]), pa.array([n for _, n in top], pa.int64())], names=["token", "n"])

    top = docs.select(text).mapInArrow(summary, "token string, n long").groupBy("token").agg(F.sum("n").alias("n"))
    tokens = [r["token"] for r in top.orderBy(F.desc("n"), "token").limit(table_size).collect()]
    return dict(zip(tokens, _library(pretokens.load(tokenizer), tokens), strict=True))


def count_tokens(docs: DataFrame, tokenizer: str = "word_bpe_49k.json", text: str = "text", key: str = "doc_id", limit: int = 2048, longest: int = 48, cache_entries: int = 1_500_000, **options) -> DataFrame:
    """key, n_bytes, n_tokens, over_limit for each row."""
    spark = docs.sparkSession
    known = spark.sparkContext.broadcast(frequent_lengths(docs, tokenizer, text, **options))
    kind = docs.schema[key].dataType

    def count(batches):
        tok, frequent = pretokens.load(tokenizer), known.value
        special = pretokens.specials(tok)
        for b in lean(batches):
            texts = [t or "" for t in b.column(1).to_pylist()]
            n_tokens = [0] * len(texts)
            for lo, hi in slices(texts):
                cache = pretokens.Cache.of(tokenizer, cache_entries)
                split = [pretokens.WORD_END.findall(t.lower()) if pretokens.plain(t, special) else None for t in texts[lo:hi]]
                missing = pretokens.unknown(split, frequent, cache)
                new = dict(zip(missing, _library(tok, missing), strict=True))
                cache.update((t, n) for t, n in new.items() if len(t) <= longest)
                look = Tiers(frequent, cache, new)
                for i, s in enumerate(split, lo):
                    n_tokens[i] = sum(map(look.__getitem__, s)) if s is not None else len(tok.encode(texts[i], add_special_tokens=False))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n_tokens, pa.int64())], names=[key, "n_bytes", "n_tokens"])

    out = docs.select(key, text).mapInArrow(count, f"{key} {kind.simpleString()}, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)
