"""Quality classifier: regularised quadratic discriminant over transformed document statistics.

Each class has a mean and a shrinkage covariance: its own covariance blended with the pooled
diagonal, the blend chosen by held-back log loss. A score is the difference of the classes'
Mahalanobis log densities through cached Cholesky factors, plus the log prior, put through a
monotone logistic calibration fitted on held-back rows. The model is fitted on a bounded sample:
at most ``per_class`` labelled rows of each class, picked by hash of the key. Where classes are
mixed, rows weigh as many labelled rows as they stand for, so the sample's mix has no effect.

Defined results: null and empty texts are scored by their (zero) statistics; rows with a null
key or label are never learned from; with labels of fewer than two classes every score is the
share of label 1 (0.5 without labels); repeated rows give repeated rows; extra columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fsmeta.llm.common import lean

STATISTICS = ("log_words", "word_length", "symbols", "pipes", "shouts", "capitals", "digits", "variety", "repeats", "stutter", "twin_lines", "stops", "line_words")
_CODE = np.zeros(256, np.int64)
for _i, _set in enumerate((b"#*$%&<>", b"|", b"!", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:?"), 1):
    _CODE[list(_set)] = _i


def statistics(text: str | None) -> list[float]:
    """Of a whole text. Shares are square-rooted and counts logged, which brings both nearer to normal."""
    text = text or ""
    w = text.split()
    n = len(w)
    bins = np.bincount(_CODE[np.frombuffer(text.encode(), np.uint8)], minlength=7)
    lines = [x for x in text.split("\n") if x and not x.isspace()]
    windows = n - 4
    repeats = 1 - len(set(zip(w, w[1:], w[2:], w[3:], w[4:], strict=False))) / windows if windows > 0 else 0.0
    per = 1 / max(1, n)
    letters = max(1, int(bins.sum()))
    return [
        np.log1p(n),
        np.log1p(len(text) * per),
        (bins[1] * per) ** 0.5,
        (bins[2] * per) ** 0.5,
        (bins[3] * per) ** 0.5,
        (bins[4] / letters) ** 0.5,
        (bins[5] / letters) ** 0.5,
        np.log1p(len(set(w))) / np.log1p(n) if n else 1.0,
        repeats**0.5,
        (sum(map(eq, w, w[1:])) * per) ** 0.5,
        ((len(lines) - len(set(lines))) / max(1, len(lines))) ** 0.5,
        (bins[6] * per) ** 0.5,
        np.log1p(n / max(1, len(lines))),
    ]


@dataclass
class Gaussian:
    mean: np.ndarray
    factor: np.ndarray  # inverse of the Cholesky factor
    log_det: float

    @classmethod
    def fit(cls, x: np.ndarray, pooled: np.ndarray, blend: float) -> Gaussian:
        cov = np.cov(x, rowvar=False, bias=True) if len(x) > 1 else np.zeros((x.shape[1],) * 2)
        low = np.linalg.cholesky((1 - blend) * cov + blend * np.diag(pooled))
        return cls(x.mean(0), np.linalg.inv(low), 2 * float(np.log(np.diag(low)).sum()))

    def log_density(self, x: np.ndarray) -> np.ndarray:
        return -0.5 * (((x - self.mean) @ self.factor.T) ** 2).sum(1) - 0.5 * self.log_det


@dataclass
class Model:
    prior: float
    good: Gaussian | None = None
    bad: Gaussian | None = None
    slope: float = 1.0
    shift: float = 0.0

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.good.log_density(x) - self.bad.log_density(x) + np.log(self.prior / (1 - self.prior))

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.good is None:
            return np.full(len(x), self.prior)
        return 1 / (1 + np.exp(-np.clip(self.slope * squash(self.margin(x)) + self.shift, -60, 60)))


def squash(z: np.ndarray) -> np.ndarray:
    """Signed logarithm: margins of a quadratic discriminant spread over orders of magnitude."""
    return np.sign(z) * np.log1p(np.abs(z))


def calibrate(z: np.ndarray, y: np.ndarray, weight: np.ndarray, steps: int = 60) -> tuple[float, float]:
    """Logistic fit of y on z, rows weighted, by damped Newton steps."""
    a = np.stack([z, np.ones_like(z)], 1)
    w = np.array([1.0, 0.0])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        h = (a * (weight * p * (1 - p))[:, None]).T @ a + 1e-2 * np.eye(2)
        w -= np.clip(np.linalg.solve(h, a.T @ (weight * (p - y)) + 1e-2 * (w - [1, 0])), -1, 1)
    return max(float(w[0]), 0.05), float(w[1])


def train(x: np.ndarray, y: np.ndarray, prior: float, weight: np.ndarray | None = None, blends: tuple[float, ...] = (0.02, 0.05, 0.1, 0.2, 0.4)) -> Model:
    """``weight``: labelled rows that each row stands for (1 by default)."""
    if len(set(y.tolist())) < 2:
        return Model(prior)
    weight = np.ones(len(x)) if weight is None else weight / weight.mean()
    held = np.arange(len(x)) % 4 == 3
    if min(np.bincount(y[held], minlength=2).min(), np.bincount(y[~held], minlength=2).min()) < 2:
        held[:] = False

    def build(rows: np.ndarray, blend: float) -> Model:
        xs, ys = x[rows], y[rows]
        mean = np.average(xs, axis=0, weights=weight[rows])
        pooled = np.maximum(np.average((xs - mean) ** 2, axis=0, weights=weight[rows]), 1e-4)
        return Model(prior, Gaussian.fit(xs[ys == 1], pooled, blend), Gaussian.fit(xs[ys == 0], pooled, blend))

    best = None
    check = held if held.any() else ~held
    for blend in blends:
        m = build(~held, blend)
        m.slope, m.shift = calibrate(squash(m.margin(x[check])), y[check], weight[check])
        p = np.clip(m.score(x[check]), 1e-9, 1 - 1e-9)
        loss = -np.average(y[check] * np.log(p) + (1 - y[check]) * np.log(1 - p), weights=weight[check])
        if best is None or loss < best[0]:
            best = (loss, blend, m.slope, m.shift)
    m = build(np.ones(len(x), bool), best[1])
    m.slope, m.shift = best[2], best[3]
    return m


def fit(docs: DataFrame, labels: DataFrame, learn: Column, key: str = "doc_id", text: str = "text", label: str = "quality", per_class: int = 3000) -> Model:
    """``learn`` picks, by key column ``k``, the labelled rows to learn from."""
    known = labels.select(labels[key].alias("k"), labels[label].cast("int").alias("y")).filter(F.col("k").isNotNull() & F.col("y").isin(0, 1) & learn)
    sizes = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}  # two rows at most
    prior = (sizes.get(1, 0) + 1) / (sum(sizes.values()) + 2)
    # a threshold on the hash first: it lets through the sample and ten standard deviations, so that few rows are ranked
    luck = F.xxhash64("k") / 2.0**64 + 0.5
    few = known.filter(luck * F.when(F.col("y") == 1, sizes.get(1, 0)).otherwise(sizes.get(0, 0)) < per_class + 10 * per_class**0.5 + 100)
    rank = F.row_number().over(Window.partitionBy("y").orderBy(F.xxhash64("k"), "k"))
    picked = few.withColumn("r", rank).filter(F.col("r") <= per_class).select("k", "y")
    chosen = docs.select(docs[key].alias("k"), docs[text].alias("t")).join(F.broadcast(picked), "k")

    def measure(batches):
        for b in lean(batches):
            stats = [statistics(t) for t in b.column("t").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("k"), b.column("y"), pa.array(stats, pa.list_(pa.float64()))], names=["k", "y", "x"])

    kind = chosen.schema["k"].dataType.simpleString()
    sample = chosen.mapInArrow(measure, f"k {kind}, y int, x array<double>").toArrow().sort_by([("k", "ascending"), ("y", "ascending")])
    if not len(sample):
        return Model(0.5)
    y = sample["y"].to_numpy()
    stands_for = [max(1.0, sizes.get(c, 0) / per_class) for c in (0, 1)]
    return train(np.array(sample["x"].to_pylist()), y, prior, np.array(stands_for)[y])


def score(docs: DataFrame, model: Model, text: str = "text", keep: tuple[str, ...] | None = None, name: str = "score") -> DataFrame:
    """The kept columns (all by default) and the score of each row, in a column called ``name``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    keep = tuple(docs.columns) if keep is None else keep
    rows = docs.select(*[docs[c] for c in keep], docs[text].alias("_measured"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields[:-1])

    def rate(batches):
        for b in lean(batches):
            texts = b.column(b.num_columns - 1).to_pylist()
            s = shared.value.score(np.array([statistics(t) for t in texts]).reshape(len(texts), len(STATISTICS)))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(s, pa.float64())], names=[*keep, name])

    return rows.mapInArrow(rate, f"{schema}, `{name}` double")
