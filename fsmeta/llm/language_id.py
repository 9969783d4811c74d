"""Language identification: averaged hashed subword embeddings under a linear softmax.

A text is the mean of the embeddings of its hashed byte 2-, 3- and 4-grams inside words (with
word edges); a linear softmax scores it. Both layers are trained by stochastic gradient
descent in numpy on a bounded sample of labelled rows: at most ``per_language`` rows of each
of every language (less where there are many, see ``fit``), picked by hash of the key. A part of the sample
is held back to fit the temperature of the probabilities and the rejection threshold: the
lowest confidence above which held-back predictions are right at ``target_precision``.

Defined results: null text or a text without any letter is ``und`` with score 0; ties go to
the language first by code point; with no labelled row all texts are ``und``; null keys are
never learned from; repeated rows give repeated rows. Whole texts are read, in pieces of
bounded size.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fsmeta.llm.common import lean, text_bytes
from fsmeta.plans import workspace

BUCKETS, ORDERS, PIECE = 1 << 13, (2, 3, 4), 1 << 19


def _edges_table() -> np.ndarray:
    """Bytes as they are hashed: ASCII letters and bytes of other scripts stay, the rest is a word edge."""
    t = np.arange(256, dtype=np.uint8)
    letter = (t >= 0x61) & (t <= 0x7A) | (t >= 0x80)
    t[~letter] = 0x20
    return t


EDGES = _edges_table()


def gram_buckets(piece: np.ndarray, ends: np.ndarray):
    """Bucket of each n-gram start for each order; 0 stands for none. ``ends``: ends of texts in the piece."""
    x = piece.astype(np.uint32)
    space = piece == 0x20
    for n in ORDERS:
        m = max(0, len(x) - n + 1)
        code = np.zeros(m, np.uint32)
        for j in range(n):
            code = (code << np.uint32(8)) | x[j : j + m]
        bucket = ((code * np.uint32(2654435761)) >> np.uint32(32 - 13)) + np.uint32(1)
        bad = space[:m] & space[n - 1 : n - 1 + m] if n == 2 else space[1 : 1 + m].copy()
        for j in range(2, n - 1):
            bad |= space[j : j + m]
        bucket[bad] = 0
        for j in range(1, n):
            at = ends - j
            bucket[at[(at >= 0) & (at < m)]] = 0
        yield bucket


def pieces(data: np.ndarray, offsets: np.ndarray):
    """(texts' indices, their starts in the piece, piece with look-ahead, ends in it, length without look-ahead)."""
    some = np.flatnonzero(np.diff(offsets) > 0)
    starts, ends = offsets[some], offsets[some + 1]
    for lo in range(0, len(data), PIECE):
        hi = min(len(data), lo + PIECE)
        a, b = np.searchsorted(ends, lo, "right"), np.searchsorted(starts, hi, "left")
        piece = EDGES[data[lo : min(len(data), hi + max(ORDERS) - 1)]]
        yield some[a:b], np.maximum(starts[a:b] - lo, 0), piece, ends[a:b] - lo, hi - lo


def sums(column: pa.Array, weights: np.ndarray) -> np.ndarray:
    """Sum of ``weights`` rows over the n-grams of each text, the last column counts them."""
    data, offsets = text_bytes(pc.utf8_lower(column))
    out = np.zeros((len(column), weights.shape[1] + 1))
    table = np.vstack([np.zeros(weights.shape[1] + 1), np.hstack([weights, np.ones((len(weights), 1))])]).astype(np.float32)
    for texts, starts, piece, ends, n in pieces(data, offsets):
        total = np.zeros((n, table.shape[1]), np.float32)
        for bucket in gram_buckets(piece, ends):
            total[: len(bucket)] += table[bucket[:n]]
        out[texts] += np.add.reduceat(total, starts, axis=0, dtype=np.float64)
    return out


def counts(column: pa.Array):
    """Per text: the buckets it has and their counts."""
    data, offsets = text_bytes(pc.utf8_lower(column))
    for i in range(len(column)):
        own, seen = data[offsets[i] : offsets[i + 1]], np.zeros(BUCKETS + 1, np.int64)
        for _, _, piece, ends, n in pieces(own, np.array([0, len(own)])):
            for bucket in gram_buckets(piece, ends):
                seen += np.bincount(bucket[:n], minlength=BUCKETS + 1)
        at = np.flatnonzero(seen[1:])
        yield at.tolist(), seen[1:][at].tolist()


@dataclass
class Model:
    languages: list[str]
    table: np.ndarray  # buckets x languages: embeddings times the output layer
    bias: np.ndarray
    temperature: float
    threshold: float

    def predict(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        s = sums(column, self.table)
        p = softmax((s[:, :-1] / np.maximum(1, s[:, -1:]) + self.bias) / self.temperature)
        return p.argmax(1), p.max(1)


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


class Shares:
    """Rows of bucket shares, kept as the buckets that each has; a few rows at a time become dense."""

    def __init__(self, buckets: list[np.ndarray], counts: list[np.ndarray]):
        self.at = buckets
        self.value = [(n / n.sum()).astype(np.float32) for n in counts]

    def __len__(self) -> int:
        return len(self.at)

    def rows(self, which: np.ndarray) -> np.ndarray:
        out = np.zeros((len(which), BUCKETS), np.float32)
        for i, r in enumerate(which.tolist()):
            out[i, self.at[r]] = self.value[r]
        return out

    def times(self, table: np.ndarray, which: np.ndarray) -> np.ndarray:
        return np.concatenate([self.rows(part) @ table for part in np.array_split(which, -(-len(which) // 256))])


def train(x: Shares, y: np.ndarray, languages: list[str], dim: int = 16, epochs: int = 40, rate: float = 8.0, batch: int = 32, target_precision: float = 0.99, seed: int = 7) -> Model:
    """Every fifth row is held back for calibration."""
    rng = np.random.default_rng(seed)
    held = np.arange(len(x)) % 5 == 4
    if held.sum() < 20:
        held[:] = False
    fit = np.flatnonzero(~held)
    e = rng.normal(0, 0.3, (BUCKETS, dim)).astype(np.float32)
    w, b = np.zeros((dim, len(languages)), np.float32), np.zeros(len(languages), np.float32)
    for epoch in range(epochs):
        step = rate * (1 - epoch / epochs)
        for at in np.array_split(rng.permutation(fit), max(1, len(fit) // batch)):
            xb = x.rows(at)
            h = xb @ e
            g = softmax(h @ w + b)
            g[np.arange(len(at)), y[at]] -= 1
            g /= len(at)
            down = g @ w.T
            w -= 0.2 * step * (h.T @ g)
            b -= 0.02 * step * g.sum(0)
            e -= 4 * step * (xb.T @ down)
    table = e @ w
    check = np.flatnonzero(held) if held.any() else fit
    z = x.times(table, check) + b
    want = np.full((len(check), len(languages)), 0.005 / len(languages))  # smoothed, so that confidence stays finite
    want[np.arange(len(check)), y[check]] += 0.995
    temperature = min(np.geomspace(0.05, 10, 60), key=lambda t: -(want * np.log(softmax(z / t) + 1e-12)).sum(1).mean())
    p = softmax(z / temperature)
    order = np.argsort(-p.max(1))
    right = np.cumsum(p.argmax(1)[order] == y[check][order]) / np.arange(1, len(check) + 1)
    good = np.flatnonzero(right >= target_precision)
    threshold = float(p.max(1)[order[good[-1]]]) if len(good) else 1.0
    return Model(languages, table, b, float(temperature), threshold)


def fit(docs: DataFrame, learn: Column, key: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = 700, sample_rows: int = 44_800, least: int = 20, **options) -> Model | None:
    """All languages are learned; with many, each gives its share of ``sample_rows``, but ``least`` rows where it has them."""
    known = docs.filter(learn & docs[lang].isNotNull() & docs[key].isNotNull()).select(docs[key].alias("k"), docs[text].alias("t"), docs[lang].cast("string").alias("l"))
    rows = known.select("k", "l")
    sizes = workspace.store(rows.groupBy("l").agg(F.count("*").alias("n")), "languages")
    share = min(per_language, max(least, sample_rows // max(1, sizes.count())))
    # a threshold on the hash first: it lets through the share and ten standard deviations, so that few rows are ranked
    luck = F.xxhash64("k") / 2.0**64 + 0.5
    few = rows.join(sizes, "l").filter(luck * F.col("n") < share + 10 * share**0.5 + 100)
    rank = F.row_number().over(Window.partitionBy("l").orderBy(F.xxhash64("k"), "k"))
    picked = few.withColumn("r", rank).filter(F.col("r") <= share).select("k").distinct()
    chosen = known.join(F.broadcast(picked), "k", "left_semi").select("k", "t", "l")

    def features(batches):
        for b in lean(batches):
            at, n = zip(*counts(b.column(1)), strict=True) if len(b) else ((), ())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(at, pa.list_(pa.int32())), pa.array(n, pa.list_(pa.int64()))], names=["k", "l", "at", "n"])

    kind = chosen.schema["k"].dataType.simpleString()
    sample = chosen.mapInArrow(features, f"k {kind}, l string, at array<int>, n array<long>").toArrow().sort_by([("k", "ascending")])
    sample = sample.filter(pc.greater(pc.list_value_length(sample["at"]), 0))
    names = sorted(set(sample["l"].to_pylist()))
    if not names:
        return None
    x = Shares(*([v.values.to_numpy() for v in sample[c]] for c in ("at", "n")))
    place = {v: i for i, v in enumerate(names)}
    y = np.array([place[v] for v in sample["l"].to_pylist()])
    return train(x, y, names, **options)


def identify(docs: DataFrame, model: Model | None, key: str = "doc_id", text: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """The kept columns, lang_pred, score and rejected (below the calibrated threshold) for each row."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)
    rows = docs.select(key, *keep, F.col(text).alias("_t"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])
    names_out = [key, *keep, "lang_pred", "score", "rejected"]

    def label(batches):
        m = shared.value
        for b in lean(batches):
            column = b.column(b.num_columns - 1)
            letter = pc.fill_null(pc.match_substring_regex(column, r"\p{L}"), False).to_numpy(zero_copy_only=False)
            if m is None or not len(b):
                names, score, low = ["und"] * len(b), np.zeros(len(b)), [True] * len(b)
            else:
                best, p = m.predict(column)
                names = [m.languages[i] if ok else "und" for i, ok in zip(best, letter, strict=True)]
                score = np.where(letter, np.round(p, 6), 0.0)
                low = (~letter | (p < m.threshold)).tolist()
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(names), pa.array(score), pa.array(low)], names=names_out)

    return rows.mapInArrow(label, f"{schema}, lang_pred string, score double, rejected boolean")
