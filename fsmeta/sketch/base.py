"""One interface to all summarizers: partial, merge, quantiles.

The numpy ones are built per task while rows stream through, merged in two levels, and give n, min and max
exactly beside their estimates. Sketches are shuffled, and in their place the values of groups that are too small for one.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.sketch import dd
from fsmeta.sketch.exact import exact, melt
from fsmeta.sketch.req import Req
from fsmeta.sketch.tdigest import TDigest

NUMPY = {"req": Req, "tdigest": TDigest}
ALGORITHMS = ("exact", "dd", "kll", "req", "tdigest", "gk")


def _codes(columns: list[pa.Array]) -> tuple[np.ndarray, np.ndarray]:
    """(group of each row, a row of each group)."""
    code = np.zeros(len(columns[0]), np.int64)
    for c in columns:
        d = c.dictionary_encode(null_encoding="encode")
        code = code * (len(d.dictionary) + 1) + d.indices.to_numpy(zero_copy_only=False)
        _, first, code = np.unique(code, return_index=True, return_inverse=True)
    return code, first


class _Growing:
    """A sketch with a buffer of values that it has not taken in yet; while it is small, the values themselves."""

    BUFFER, SMALL = 4096, 256

    def __init__(self, make):
        self.make, self.sketch, self.parts, self.held, self.n, self.low, self.high = make, None, [], 0, 0, np.inf, -np.inf

    def count(self, n: int, low: float, high: float) -> None:
        self.n, self.low, self.high = self.n + n, min(self.low, low), max(self.high, high)

    def add(self, v: np.ndarray) -> None:
        self.parts.append(v)
        self.held += len(v)
        if self.held >= self.BUFFER:
            self.settle()

    def merge(self, other) -> None:
        if self.sketch is None:
            self.sketch = other
        else:
            self.sketch.merge(other)

    def settle(self) -> None:
        if self.parts:
            self.sketch = self.make() if self.sketch is None else self.sketch
            self.sketch.add(np.sort(np.concatenate(self.parts)))
            self.parts, self.held = [], 0

    def dump(self, small: int = SMALL) -> tuple[bool, bytes]:
        """(whether it is values, bytes)."""
        if self.sketch is None and self.n <= small:
            return True, np.sort(np.concatenate(self.parts)).tobytes()
        self.settle()
        return False, self.sketch.dump()


_STATE = "plain boolean, sketch binary, n long, low double, high double"


def _made(keys: list[pa.Array], names: list[str], made: list[_Growing], small: int = _Growing.SMALL) -> pa.RecordBatch:
    plain, raw = zip(*(g.dump(small) for g in made), strict=True)
    state = [pa.array(plain), pa.array(raw, pa.binary()), pa.array([g.n for g in made], pa.int64()), pa.array([g.low for g in made], pa.float64()), pa.array([g.high for g in made], pa.float64())]
    return pa.RecordBatch.from_arrays([*keys, *state], names=[*names, "plain", "sketch", "n", "low", "high"])


def _types(df: DataFrame) -> str:
    return df.schema.simpleString().removeprefix("struct<").removesuffix(">").replace(":", " ")


def partial(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], algo: str, held: int = 20_000, buffered: int = 4_000_000, block: int = 500_000, **params) -> DataFrame:
    """by..., attr, part, plain, sketch, n, low, high: one row for each group in each block of rows that is small there, with
    its values, and a sketch for each other group in each task. A task holds at most ``held`` sketches, some ``buffered``
    values for them, and a block."""
    kind = NUMPY[algo]
    rows = df.select(*by, *[F.col(a).cast("double").alias(f"_v{i}") for i, a in enumerate(attrs)])
    names = [*by, "attr", "part"]

    def build(batches):
        from pyspark import TaskContext

        part, own, waiting = 1 + TaskContext.get().partitionId() % 31, {}, 0
        types = None

        def flush():
            cols = [pa.array(c, t) for c, t in zip(zip(*own, strict=True), [*types, pa.string()], strict=True)]
            return _made([*cols, pa.array([part] * len(own), pa.int32())], names, list(own.values()), -1)

        def group(held_back):
            """Small groups of these rows as they are; the others go to their sketches."""
            nonlocal waiting
            t = pa.Table.from_batches(held_back).combine_chunks()
            columns = [c.chunk(0) for c in t.columns]
            at, first = _codes(columns[: len(by)]) if by else (np.zeros(t.num_rows, np.int64), np.zeros(1, np.int64))
            order = np.argsort(at, kind="stable")
            at = at[order]
            for attr, column in zip(attrs, columns[len(by) :], strict=True):
                there = column.is_valid().to_numpy(zero_copy_only=False)[order]
                values, whose = column.to_numpy(zero_copy_only=False)[order][there], at[there]
                if not len(values):
                    continue
                n = np.bincount(whose, minlength=len(first))
                groups = np.flatnonzero(n)
                n = n[groups]
                begin = np.cumsum(n) - n
                low, high = np.fmin.reduceat(values, begin), np.fmax.reduceat(values, begin)
                few = n <= _Growing.SMALL
                if few.any():
                    ends = np.concatenate([[0], np.cumsum(n[few])]).astype(np.int32) * np.int32(8)
                    raw = pa.Array.from_buffers(pa.binary(), int(few.sum()), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(values[np.repeat(few, n)]))])
                    keys = [c.take(pa.array(first[groups[few]])) for c in columns[: len(by)]]
                    k = len(raw)
                    yield pa.RecordBatch.from_arrays([*keys, pa.array([attr] * k, pa.string()), pa.array(np.zeros(k, np.int32)), pa.array(np.ones(k, bool)), raw, pa.array(n[few]), pa.array(low[few]), pa.array(high[few])], names=[*names, "plain", "sketch", "n", "low", "high"])
                many = np.flatnonzero(~few)
                keys = zip(*(c.take(pa.array(first[groups[many]])).to_pylist() for c in columns[: len(by)]), strict=True) if by else [()] * len(many)
                for key, g in zip(keys, many.tolist(), strict=True):
                    if (*key, attr) not in own:
                        own[(*key, attr)] = _Growing(lambda: kind(**params))
                    own[(*key, attr)].add(values[begin[g] : begin[g] + n[g]])
                    own[(*key, attr)].count(int(n[g]), float(low[g]), float(high[g]))
                    waiting += int(n[g])

        back, size = [], 0
        for b in batches:
            if not b.num_rows:
                continue
            types = [f.type for f in b.schema][: len(by)]
            back.append(b)
            size += b.num_rows
            if size < block:
                continue
            yield from group(back)
            back, size = [], 0
            if waiting > buffered:
                for g in own.values():
                    g.settle()
                waiting = 0
            if len(own) > held:
                yield flush()
                own.clear()
        if back:
            yield from group(back)
        if own:
            yield flush()

    kinds = _types(df.select(*by)) + ", " if by else ""
    return rows.mapInArrow(build, f"{kinds}attr string, part int, {_STATE}")


def merge(parts: DataFrame, keys: tuple[str, ...], algo: str, small: int = _Growing.SMALL, **params) -> DataFrame:
    """keys..., plain, sketch, n, low, high. Sketches of a key are merged as they stream by, the largest first, then values
    are added; up to ``small`` values stay values."""
    kind = NUMPY[algo]
    rows = parts.select(*keys, "plain", "sketch", "n", "low", "high").repartition(*keys).sortWithinPartitions(*keys, "plain", F.desc("n"), "sketch")

    def join(batches):
        types = None

        def out():
            found = [pa.array(c, t) for c, t in zip(zip(*(k for k, _ in done), strict=True), types, strict=True)]
            return _made(found, list(keys), [g for _, g in done], small)

        now, done = None, []
        for b in batches:
            types = [b.schema.field(k).type for k in keys]
            for *key, plain, raw, n, low, high in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if key != now:
                    if len(done) >= 1024:
                        yield out()
                        done = []
                    now = key
                    done.append((key, _Growing(lambda: kind(**params))))
                g = done[-1][1]
                g.count(n, low, high)
                if plain:
                    g.add(np.frombuffer(raw))
                else:
                    g.merge(kind.load(raw))
        if done:
            yield out()

    return rows.mapInArrow(join, f"{_types(parts.select(*keys))}, {_STATE}")


def estimates(merged: DataFrame, keys: tuple[str, ...], qs: tuple[float, ...], algo: str) -> DataFrame:
    """keys..., q (array), n; clamped by the exact ends."""
    kind = NUMPY[algo]
    schema = merged.select(*keys).schema.simpleString().removeprefix("struct<").removesuffix(">").replace(":", " ")

    def read(batches):
        for b in batches:
            q = [[min(max(v, lo), hi) for v in kind.load(s).quantiles(qs)] for s, lo, hi in zip(*(b.column(c).to_pylist() for c in ("sketch", "low", "high")), strict=True)]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array(q, pa.list_(pa.float64())), b.column("n")], names=[*keys, "q", "n"])

    return merged.mapInArrow(read, f"{schema}, q array<double>, n long")


def quantiles(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], qs: tuple[float, ...], algo: str = "dd", **params) -> DataFrame:
    """by..., attr, q (array of estimates), by the named summarizer. Groups without values give no row."""
    keys = (*by, "attr")
    if algo == "exact":
        return exact(df, by, attrs, qs)
    if algo == "dd":
        alpha = params.get("alpha", 0.01)
        return dd.quantiles(dd.buckets(df, by, attrs, alpha), keys, qs, alpha)
    rows = melt(df, by, attrs)
    if algo == "kll":
        s = rows.groupBy(*keys).agg(F.kll_sketch_agg_double("value", F.lit(params.get("k", 200))).alias("s"))
        return s.select(*keys, F.array(*[F.kll_sketch_get_quantile_double("s", F.lit(float(q))) for q in qs]).alias("q"))
    if algo == "gk":
        return rows.groupBy(*keys).agg(F.percentile_approx("value", list(qs), params.get("accuracy", 10_000)).alias("q"))
    parts = partial(df, by, attrs, algo, **params)
    params = {k: v for k, v in params.items() if k not in ("held", "buffered", "block")}  # how much a task holds
    merged = merge(merge(parts, (*keys, "part"), algo, **params), keys, algo, -1, **params)
    return estimates(merged, keys, qs, algo).drop("n")


def footprint(df: DataFrame, by: tuple[str, ...], attrs: tuple[str, ...], alpha: float = 0.01) -> DataFrame:
    """by..., attr: buckets that the bounded sketch holds against the distinct values that an exact table does."""
    b = dd.buckets(df, by, attrs, alpha).groupBy(*by, "attr").agg(F.count("*").alias("buckets"))
    d = melt(df, by, attrs).groupBy(*by, "attr").agg(F.countDistinct("value").alias("distinct_values"))
    return b.join(d, [*by, "attr"])
