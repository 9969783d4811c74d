"""Benchmark decontamination by q-gram counting in diagonal bands and banded alignment.

An item of m characters that stands in a document with at most k edits shares at least
m - q + 1 - k q of its q-grams with it (q-gram lemma), all on diagonals that drift by no more
than k. Shared q-grams are counted in bands of 2 (k + 1) diagonals that overlap by half; bands
that reach the bound are regions, which a banded semi-global alignment verifies. k is
``budget`` times m for every item, and q is 8, or as much less as a short item needs for a bound
of one.

Texts are compared lower-cased, with runs of ASCII signs and white space as one blank, as
UTF-8 bytes. The item table is worked on in blocks of bounded size, one after the other: each is
broadcast, held against all documents, and let go.

Defined results: null and empty texts and items match nothing; a row that repeats is matched
each time; the best region of each item (fewest edits, then first) is reported; extra columns
are not read; whole texts are read in pieces that overlap by the longest item and its budget;
shared q-grams are expanded in steps of bounded size, so repetitive texts and items take no more memory.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from fsmeta.llm.common import lean, text_bytes
from fsmeta.plans import workspace

#: Longest q; bytes of text and of items worked on at once; bits of the filter of q-grams; shared q-grams expanded at once.
Q, PIECE, BLOCK_BYTES, FILLED, STEP = 8, 1 << 20, 4 << 20, 22, 1 << 20


def _plain() -> np.ndarray:
    t = np.arange(256, dtype=np.uint8)
    keep = (t >= 0x80) | (t >= 0x30) & (t <= 0x39) | (t >= 0x61) & (t <= 0x7A)
    t[0x41:0x5B] += 0x20
    t[~(keep | (np.arange(256) >= 0x41) & (np.arange(256) < 0x5B))] = 0x20
    return t


PLAIN = _plain()


def normal(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Comparable bytes of the texts end to end, and their offsets."""
    data, offsets = text_bytes(pc.utf8_lower(column))
    data = PLAIN[data]
    blank = data == 0x20
    first = np.zeros(len(data) + 1, bool)
    first[offsets] = True
    keep = ~blank
    keep[1:] |= ~blank[:-1]
    keep &= ~(blank & first[:-1])
    some = np.flatnonzero(np.diff(offsets) > 0)
    left = np.zeros(len(offsets), np.int64)
    if len(some):
        left[some + 1] = np.add.reduceat(keep, offsets[some], dtype=np.int64)
    return data[keep], np.cumsum(left)


def gram_size(m: int, k: int) -> int:
    """The largest q up to Q with which an item of m bytes shares at least one q-gram after k edits."""
    return min(Q, m // (k + 1))


class Postings:
    """q-grams of all items of one q."""

    def __init__(self, q: int, members: list[int], items: list[bytes]):
        self.q = q
        grams, owner, place = [], [], []
        for j in members:
            c = codes(np.frombuffer(items[j], np.uint8), q)[: len(items[j]) - q + 1]
            grams.append(c)
            owner.append(np.full(len(c), j))
            place.append(np.arange(len(c)))
        g, owner, place = np.concatenate(grams), np.concatenate(owner), np.concatenate(place)
        order = np.argsort(g, kind="stable")
        self.owner, self.place = owner[order], place[order]
        self.grams, self.start = np.unique(g[order], return_index=True)
        self.start = np.append(self.start, len(g))
        self.filled = np.zeros(1 << FILLED, bool)
        self.filled[spread(self.grams)] = True


class Index:
    """The items of a block in comparable form, with their edit budgets and q-grams."""

    def __init__(self, ids: list, items: list[str], budget: float):
        flat, at = normal(pa.array(items, pa.string()))
        self.ids, self.items, edits, least, sizes = [], [], [], [], {}
        for i, own in zip(ids, (flat[a:b] for a, b in zip(at[:-1], at[1:], strict=True)), strict=True):
            own = own[:-1] if len(own) and own[-1] == 0x20 else own
            m = len(own)
            if not m:
                continue
            k = int(budget * m)
            q = gram_size(m, k)
            sizes.setdefault(q, []).append(len(self.ids))
            self.ids.append(i)
            self.items.append(own.tobytes())
            edits.append(k)
            least.append(m - q + 1 - k * q)
        self.size = np.array([len(x) for x in self.items], np.int64)
        self.edits, self.least = np.array(edits, np.int64), np.array(least, np.int64)
        self.postings = [Postings(q, members, self.items) for q, members in sorted(sizes.items())]
        self.reach = int((self.size + 3 * self.edits).max()) + 4 if len(self.items) else 0


def codes(data: np.ndarray, q: int = Q) -> np.ndarray:
    """The q bytes from each place, as a number; beyond the end stand zero bytes."""
    raw = np.ndarray((len(data),), "<u8", np.ascontiguousarray(data).tobytes() + b"\0" * 8, strides=(1,))
    return raw & np.uint64((1 << (8 * q)) - 1)


def spread(c: np.ndarray) -> np.ndarray:
    return ((c * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - FILLED)).astype(np.int64)


def banded(item: bytes, region: bytes, k: int) -> tuple[int, int] | None:
    """(edits, end in region) of the cheapest place of the item in the region, if at most k edits.

    Semi-global: the place may begin and end anywhere. Only cells whose diagonal lies in the region's
    slack take part, a row at a time; insertions within a row are a running minimum.
    """
    at = region.find(item)
    if at >= 0:
        return 0, at + len(item)
    m, slack = len(item), max(0, len(region) - len(item)) + k
    r = np.frombuffer(region, np.uint8)
    far = 1 << 20
    # cell (i, d): i bytes of the item against the region up to place i + d - k
    d = np.arange(slack + k + 1) - k
    row = np.where((d >= 0) & (d <= len(r)), 0, far)
    steps = np.arange(len(d))
    padded = np.concatenate([np.zeros(k + 1, np.uint8), r, np.zeros(m + len(d) + 1, np.uint8)])
    for i in range(1, m + 1):
        chars = padded[i : i + len(d)]  # region byte before place i + d
        place = i + d
        ok = (place >= 0) & (place <= len(r))
        change = row + ((chars != item[i - 1]) | (place < 1))
        drop = np.append(row[1:], far) + 1
        row = np.where(ok, np.minimum(change, drop), far)
        row = np.minimum.accumulate(row - steps) + steps
        row = np.where(ok, row, far)
        if row.min() > k:
            return None
    best = int(row.argmin())
    return (int(row[best]), m + int(d[best])) if row[best] <= k else None


def bands(index: Index, post: Postings, data: np.ndarray, offsets: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, item, band) of the bands in data[lo:hi] that reach their item's bound."""
    c = codes(data[lo : min(len(data), hi + post.q - 1)], post.q)[: hi - lo]
    at = np.flatnonzero(post.filled[spread(c)])
    found = np.minimum(np.searchsorted(post.grams, c[at]), len(post.grams) - 1)
    hit = post.grams[found] == c[at]
    at, found = at[hit] + lo, found[hit]
    text = np.searchsorted(offsets, at, "right") - 1
    hit = at + post.q <= offsets[text + 1]
    at, found, text = at[hit], found[hit], text[hit]
    none = np.zeros(0, np.int64)
    if not len(at):
        return none, none, none
    many, wide, first = len(index.items), PIECE + 3 * index.reach, int(text[0])
    n = post.start[found + 1] - post.start[found]
    upto, keys, counts, held, a = np.cumsum(n), [], [], 0, 0
    while a < len(at):
        z = max(a + 1, int(np.searchsorted(upto, (upto[a - 1] if a else 0) + STEP, "right")))
        m = n[a:z]
        which = np.repeat(np.arange(a, z), m)
        posting = np.arange(len(which)) - np.repeat(np.cumsum(m) - m, m) + np.repeat(post.start[found[a:z]], m)
        item = post.owner[posting]
        band = (at[which] - post.place[posting] - lo + index.reach) // (index.edits[item] + 1)
        key = ((text[which] - first) * many + item) * wide + band
        # each shared q-gram counts in the band that starts at its half step and in the one before
        key, count = np.unique(np.concatenate([key, key - 1]), return_counts=True)
        keys.append(key)
        counts.append(count)
        held += len(key)
        a = z
        if held > 4 * STEP:  # what steps have in common becomes one
            keys, counts = ([x] for x in _added(keys, counts))
            held = 0
    key, count = _added(keys, counts)
    key = key[count >= index.least[(key // wide) % many]]
    t, j = np.divmod(key // wide, many)
    return t + first, j, key % wide


def _added(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    if len(keys) == 1:
        return keys[0], counts[0]
    key, at = np.unique(np.concatenate(keys), return_inverse=True)
    return key, np.bincount(at, np.concatenate(counts)).astype(np.int64)


def search(index: Index, data: np.ndarray, offsets: np.ndarray):
    """(text, item, edits, end) of every item in every text, the best of each."""
    best: dict[tuple[int, int], tuple[int, int]] = {}
    for post in index.postings:
        for lo in range(0, len(data), PIECE):
            hi = min(len(data), lo + PIECE + index.reach)
            for t, j, band in zip(*(x.tolist() for x in bands(index, post, data, offsets, lo, hi)), strict=True):
                known = best.get((t, j))
                if known is not None and not known[0]:
                    continue  # bands come in order: no later one is better than an exact place
                k, m = int(index.edits[j]), int(index.size[j])
                left = band * (k + 1) - index.reach + lo
                a, z = max(int(offsets[t]), left - k), min(int(offsets[t + 1]), left + 2 * (k + 1) + m + k)
                if (got := banded(index.items[j], data[a:z].tobytes(), k)) is not None:
                    got = (got[0], a - int(offsets[t]) + got[1])
                    if known is None or got < known:
                        best[t, j] = got
    for (t, j), (edits, end) in sorted(best.items()):
        yield t, j, edits, end


def blocks(benchmark: DataFrame, item: str, text: str, limit: int = BLOCK_BYTES):
    """The items in runs of bounded size."""
    ids, texts, held = [], [], 0
    for r in benchmark.select(item, text).toLocalIterator():
        if r[1]:
            ids.append(r[0])
            texts.append(r[1])
            held += len(r[1])
        if held >= limit:
            yield ids, texts
            ids, texts, held = [], [], 0
    if ids:
        yield ids, texts


def leaks(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", budget: float = 0.1, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """key, item_id, edits, end (of the place, in comparable bytes) for each item found in each row."""
    spark = docs.sparkSession
    kind, item_kind = docs.schema[key].dataType.simpleString(), benchmark.schema[item].dataType
    schema = f"`{key}` {kind}, item_id {item_kind.simpleString()}, edits long, end long"
    path = workspace.fresh(spark, "leaks")
    spark.createDataFrame([], schema).write.parquet(path)
    for ids, texts in blocks(benchmark, item, item_text, block_bytes):
        shared = spark.sparkContext.broadcast((ids, texts))

        def find(batches, shared=shared):
            index = None
            for b in lean(batches, 256):
                index = index or Index(*shared.value, budget)
                if not index.items:
                    return
                data, offsets = normal(b.column(1))
                got = list(search(index, data, offsets))
                if got:
                    t, j, e, z = zip(*got, strict=True)
                    yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(t)), pa.array([index.ids[x] for x in j]), pa.array(e, pa.int64()), pa.array(z, pa.int64())], names=[key, "item_id", "edits", "end"])

        docs.select(key, text).mapInArrow(find, schema).write.mode("append").parquet(path)
        shared.destroy()
    return spark.read.schema(schema).parquet(path)
