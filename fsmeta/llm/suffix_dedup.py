"""Removal of repeated byte strings by a depth-limited radix sort of suffixes.

A byte goes if a string of ``length`` bytes that covers it starts at another place too, in any
document. Only suffixes that can have an equal are sorted:

1. Every window (string of ``length`` bytes) has an anchor: of its k-byte strings the one whose
   hash is least, the leftmost of equals. The anchor depends on the window's content alone, so equal
   windows have equal anchors at equal offsets. Anchors are counted over the corpus; windows
   whose anchor occurs once are unique.
2. Runs of windows with the same repeated anchor become contexts: bytes from the first window's
   start to the last one's end. Equal contexts count as one with many occurrences.
3. The windows of all contexts of an anchor are ordered by most-significant-digit passes, first by
   anchor and offset, then by one digit of ``DIGIT`` bytes at a time, only up to ``length`` bytes;
   classes of one drop out after each pass. The classes left are exactly the repeated windows.
   Equal contexts are added up in each task before they are dealt by anchor, so a task holds the
   different contexts of an anchor. For anchors with very many of them the same passes are run as
   shuffles, one a digit, with windows as rows that are added up before each.
4. Repeated windows go back to their documents as spans.

Defined results: null text is an empty text; texts shorter than ``length`` keep every byte;
rows that repeat are each other's repetition; overlapping repetitions count; very long texts are
worked on in pieces that overlap by ``length`` - 1 bytes; extra columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fsmeta.llm.common import Rolling, lean, mix, text_bytes
from fsmeta.plans import workspace

ANCHOR, DIGIT, PIECE, PLACE = 64, 50, 1 << 19, 24
#: Repeated anchors (8 bytes each) are broadcast up to this number, and spans up to this many bytes; beyond that they are joined by shuffles.
LISTED, SPAN_BYTES = 3_000_000, 24 << 20


def window_minimum(v: np.ndarray, w: int) -> np.ndarray:
    """Least of each w values in a row, from running minima of blocks in both directions."""
    n = len(v) - w + 1
    full = np.full(-(-len(v) // w) * w, np.iinfo(np.uint64).max, np.uint64)
    full[: len(v)] = v
    blocks = full.reshape(-1, w)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[w - 1 : w - 1 + n])


def runs(data: np.ndarray, offsets: np.ndarray, length: int):
    """For runs of texts of bounded bytes: (bytes, first text, text of each run, start of that
    text's piece in the bytes, its place in the text, first and last window, anchor place, anchor hash)."""
    lo = 0
    while lo < len(offsets) - 1:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + PIECE, "right")) - 1)
        total = int(offsets[hi] - offsets[lo])
        if hi == lo + 1 and total > PIECE:
            for at in range(0, total - length + 1, PIECE):
                own = data[offsets[lo] + at : offsets[lo] + min(total, at + PIECE + length - 1)]
                if (found := _runs(own, np.array([0, len(own)]), length)) is not None:
                    yield own, lo, np.array([0]), np.array([at]), found
        else:
            own, cuts = data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
            if (found := _runs(own, cuts, length)) is not None:
                yield own, lo, cuts[:-1], np.zeros(hi - lo, np.int64), found
        lo = hi


def _runs(own: np.ndarray, cuts: np.ndarray, length: int):
    k = min(ANCHOR, length)
    if len(own) < length:
        return None
    h = Rolling(own).every(k)
    low = np.uint64((1 << PLACE) - 1)
    v = (h & ~low) | np.arange(len(h), dtype=np.uint64)
    least = window_minimum(v, length - k + 1)
    valid = np.zeros(len(own) + 1, np.int8)  # windows that stay inside one text
    some = np.diff(cuts) >= length
    valid[cuts[:-1][some]] += 1
    valid[cuts[1:][some] - length + 1] -= 1
    at = np.flatnonzero(np.cumsum(valid[: len(least)]) > 0)
    if not len(at):
        return None
    m = least[at]
    first = np.flatnonzero(np.concatenate([[True], m[1:] != m[:-1]]))
    last = np.append(first[1:], len(at)) - 1
    place = (m[first] & low).astype(np.int64)
    text = np.searchsorted(cuts, at[first], "right") - 1
    return text, at[first], at[last], place, h[place].view(np.int64)


def anchors(docs: DataFrame, text: str, length: int, rid: Column | None = None) -> DataFrame:
    """h and n (how often, summed over a batch); with ``rid`` h and rid."""
    named = rid is not None
    cols = [F.col(text).alias("t")] + ([rid.alias("rid")] if named else [])

    def find(batches):
        for b in lean(batches):
            data, offsets = text_bytes(b.column(0))
            for _, lo, _, _, (own, _, _, _, h) in runs(data, offsets, length):
                if named:
                    yield pa.RecordBatch.from_arrays([pa.array(h), b.column(1).take(pa.array(own + lo))], names=["h", "rid"])
                else:
                    u, n = np.unique(h, return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(n.astype(np.int64))], names=["h", "n"])

    return docs.select(*cols).mapInArrow(find, "h long, rid binary" if named else "h long, n long")


CONTEXT = "h long, cid binary, off int, windows int, fresh boolean, ctx binary, rid binary, lo long"
#: Contexts that an anchor may bring to one task; the passes of anchors with more are shuffles.
CROWD = 100_000


def contexts(docs: DataFrame, text: str, length: int, rid: Column, repeated: DataFrame, listed: int) -> DataFrame:
    """One row for each run of windows with a repeated anchor; ``ctx`` is null when the task gave it before."""
    spark = docs.sparkSession
    few = repeated.limit(listed + 1).select("h").toArrow()["h"].to_numpy()
    broad = len(few) <= listed
    shared = spark.sparkContext.broadcast(np.sort(few) if broad else None)
    rows = docs.select(F.col(text).alias("t"), rid.alias("rid"))
    if not broad:
        own = anchors(docs, text, length, rid).distinct().join(repeated.select("h"), "h").groupBy("rid").agg(F.collect_list("h").alias("own"))
        rows = rows.join(own, "rid").select("t", "rid", "own")

    def cut(batches):
        every, seen = shared.value, set()
        for b in lean(batches):
            data, offsets = text_bytes(b.column(0))
            rids = b.column(1)
            for own, lo, starts, places, (text_of, first, last, place, h) in runs(data, offsets, length):
                if every is not None:
                    take = np.zeros(len(h), bool)
                    if len(every):
                        take = every[np.minimum(np.searchsorted(every, h), len(every) - 1)] == h
                else:
                    mine = {i: set(b.column(2)[i + lo].as_py()) for i in set(text_of.tolist())}
                    take = np.array([x in mine[i] for i, x in zip(text_of.tolist(), h.tolist(), strict=True)], bool)
                if not take.any():
                    continue
                t, f, e, p, g = text_of[take], first[take], last[take], place[take], h[take]
                raw, off = own.tobytes(), (p - f).astype(np.int32)
                cids, ctxs = [], []
                for a, z, o in zip(f.tolist(), (e + length).tolist(), off.tolist(), strict=True):
                    c = raw[a:z]
                    cid = hashlib.blake2b(c, digest_size=16, salt=o.to_bytes(4, "little")).digest()
                    cids.append(cid)
                    ctxs.append(None if cid in seen else c)
                    seen.add(cid)
                if len(seen) > 500_000:
                    seen = set()
                yield pa.RecordBatch.from_arrays(
                    [pa.array(g), pa.array(cids, pa.binary()), pa.array(off), pa.array((e - f + 1).astype(np.int32)), pa.array([c is not None for c in ctxs]), pa.array(ctxs, pa.binary()), rids.take(pa.array(t + lo)), pa.array(f - starts[t] + places[t])],
                    names=["h", "cid", "off", "windows", "fresh", "ctx", "rid", "lo"],
                )

    return rows.mapInArrow(cut, CONTEXT)


def radix_classes(buffer: np.ndarray, start: np.ndarray, group: np.ndarray, length: int) -> np.ndarray:
    """Which of the suffixes at ``start`` share their first ``length`` bytes with another of the same group."""
    hashes, live, cls = Rolling(buffer), np.arange(len(start)), group.astype(np.uint64)
    for at in range(0, length, DIGIT):
        p = start[live]
        key = mix(hashes.ranges(p + at, p + min(length, at + DIGIT)) + cls * np.uint64(0x9E3779B97F4A7C15))
        order = np.argsort(key)
        key = key[order]
        new = np.concatenate([[True], key[1:] != key[:-1]])
        ids = np.cumsum(new) - 1
        keep = np.bincount(ids)[ids] > 1
        live, cls = live[order[keep]], ids[keep].astype(np.uint64)
        if not len(live):
            break
    out = np.zeros(len(start), bool)
    out[live] = True
    return out


def _solve(groups: list[dict], length: int) -> pa.RecordBatch | None:
    """``groups``: for each anchor its contexts {cid: [ctx, off, windows, occurrences]}. Gives cid and the runs of repeated windows."""
    flat, cids = [], []
    base, starts, keys, owner = 0, [], [], []
    for g, found in enumerate(groups):
        if len(found) == 1:
            ((cid, (ctx, _, n, times)),) = found.items()
            if times > 1:
                cids.append((cid, np.array([[0, n - 1]], np.int32).tobytes()))
            continue
        for cid, (ctx, off, n, times) in found.items():
            j = np.arange(n)
            starts.append(base + j)
            keys.append((g << 9) + (off - j) + 0)
            owner.append((cid, n, times))
            flat.append(ctx)
            base += len(ctx)
    if flat:
        same = radix_classes(np.frombuffer(b"".join(flat), np.uint8), np.concatenate(starts), np.concatenate(keys), length)
        at = 0
        for cid, n, times in owner:
            own = same[at : at + n] if times < 2 else np.ones(n, bool)
            at += n
            if own.any():
                edge = np.flatnonzero(np.diff(np.concatenate([[0], own.view(np.int8), [0]])))
                cids.append((cid, np.stack([edge[::2], edge[1::2] - 1], 1).astype(np.int32).tobytes()))
    if not cids:
        return None
    return pa.RecordBatch.from_arrays([pa.array([c for c, _ in cids], pa.binary()), pa.array([r for _, r in cids], pa.binary())], names=["cid", "runs"])


def combined(found: DataFrame, entries: int = 100_000) -> DataFrame:
    """h, cid, off, windows, ctx, times: equal contexts of one task as one row (more where it holds more than ``entries``)."""

    def add(batches):
        held: dict = {}

        def out():
            rows = [(h, cid, *v) for (h, cid), v in held.items()]
            kinds = (pa.int64(), pa.binary(), pa.int32(), pa.int32(), pa.binary(), pa.int64())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["h", "cid", "off", "windows", "ctx", "times"])

        for b in lean(batches):
            for h, cid, off, n, ctx in zip(*(c.to_pylist() for c in b.columns), strict=True):
                own = held.get((h, cid))
                if own is None:
                    held[h, cid] = [off, n, ctx, 1]
                else:
                    own[3] += 1
                    if own[2] is None:
                        own[2] = ctx
            if len(held) >= entries:
                yield out()
                held = {}
        if held:
            yield out()

    return found.select("h", "cid", "off", "windows", "ctx").mapInArrow(add, "h long, cid binary, off int, windows int, ctx binary, times long")


def repeated_runs(found: DataFrame, length: int, held_bytes: int = 4 << 20, crowd: int | None = None) -> DataFrame:
    """cid and the runs (first and last window) of it that occur elsewhere."""
    many = found.filter("fresh").groupBy("h").agg(F.count("*").alias("n")).filter(F.col("n") > (CROWD if crowd is None else crowd)).select("h")
    many = workspace.store(many, "crowds")
    if many.isEmpty():
        return _sorted_runs(found, length, held_bytes)
    # at most one anchor for every ``crowd`` contexts
    rest = found.join(F.broadcast(many), "h", "left_anti")
    return _sorted_runs(rest, length, held_bytes).unionByName(_shuffled_runs(found.join(F.broadcast(many), "h", "left_semi"), length))


def _shuffled_runs(found: DataFrame, length: int) -> DataFrame:
    """The passes for anchors with very many contexts: every window is a row with its place before the
    anchor and its digits, and each pass is a shuffle that leaves the classes of two or more."""
    times = found.groupBy("h", "cid").agg(F.count("*").alias("times"))
    texts = found.filter("fresh").select("cid", "off", "windows", "ctx").dropDuplicates(["cid"])
    digits = -(-length // DIGIT)

    def spread(batches):
        for b in lean(batches, 64):
            for h, cid, off, n, ctx, k in zip(*(c.to_pylist() for c in b.columns), strict=True):
                hashes, at = Rolling(np.frombuffer(ctx, np.uint8)), np.arange(n)
                parts = [hashes.ranges(at + d * DIGIT, at + min(length, (d + 1) * DIGIT)).view(np.int64) for d in range(digits)]
                cols = [pa.array([cid] * n, pa.binary()), pa.array(at.astype(np.int32)), pa.array([k] * n, pa.int64()), pa.array(np.full(n, h)), pa.array((off - at).astype(np.int32)), *map(pa.array, parts)]
                yield pa.RecordBatch.from_arrays(cols, names=["cid", "j", "times", "h", "place", *(f"d{d}" for d in range(digits))])

    rows = times.join(texts, "cid").select("h", "cid", "off", "windows", "ctx", "times")
    rows = rows.mapInArrow(spread, "cid binary, j int, times long, h long, place int, " + ", ".join(f"d{d} long" for d in range(digits)))
    rows = rows.withColumn("class", F.xxhash64("h", "place")).drop("h", "place")
    for d in range(digits):
        rows = workspace.store(rows.withColumn("class", F.xxhash64("class", f"d{d}")).drop(f"d{d}"), "digit")
        live = rows.groupBy("class").agg(F.sum("times").alias("_all")).filter("_all > 1").select("class")
        rows = rows.join(live, "class", "left_semi")
    per = rows.groupBy("cid").agg(F.sort_array(F.collect_list("j")).alias("js"))

    def pack(batches):
        for b in lean(batches):
            out = []
            for js in b.column(1).to_pylist():
                j = np.array(js, np.int32)
                new = np.flatnonzero(np.diff(j) > 1)
                out.append(np.stack([j[np.append(0, new + 1)], j[np.append(new, len(j) - 1)]], 1).astype(np.int32).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], names=["cid", "runs"])

    return per.mapInArrow(pack, "cid binary, runs binary")


def _sorted_runs(found: DataFrame, length: int, held_bytes: int) -> DataFrame:

    def reduce(batches):
        groups, held, now = [], 0, None
        for b in lean(batches):
            for h, cid, off, n, ctx, times in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if h != now:
                    if held >= held_bytes:
                        if (out := _solve(groups, length)) is not None:
                            yield out
                        groups, held = [], 0
                    groups.append({})
                    now = h
                own = groups[-1].get(cid)
                if own is None:
                    groups[-1][cid] = [ctx, off, n, times]
                    held += len(ctx or b"")
                else:
                    own[3] += times
                    if own[0] is None and ctx is not None:
                        own[0] = ctx
                        held += len(ctx)
        if groups and (out := _solve(groups, length)) is not None:
            yield out

    rows = combined(found).repartition("h").sortWithinPartitions("h")
    return rows.mapInArrow(reduce, "cid binary, runs binary")


def merge(pairs: np.ndarray) -> np.ndarray:
    """Sorted, disjoint [start, end) from overlapping or touching ones."""
    pairs = pairs[np.argsort(pairs[:, 0], kind="stable")]
    top = np.maximum.accumulate(pairs[:, 1])
    new = np.concatenate([[True], pairs[1:, 0] > top[:-1]])
    last = np.append(np.flatnonzero(new)[1:], len(pairs)) - 1
    return np.stack([pairs[new, 0], top[last]], 1)


def spans(found: DataFrame, same: DataFrame, length: int) -> DataFrame:
    """rid and its removed spans (packed pairs of start and end), one row a document that has any."""
    per = found.select("cid", "rid", "lo").join(same, "cid").groupBy("rid").agg(F.collect_set(F.struct("lo", "runs")).alias("parts"))

    def pack(batches):
        for b in lean(batches):
            out = []
            for parts in b.column(1).to_pylist():
                own = [np.frombuffer(p["runs"], np.int32).reshape(-1, 2).astype(np.int64) + p["lo"] for p in parts]
                out.append(merge(np.concatenate(own) + [0, length]).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], names=["rid", "spans"])

    return per.mapInArrow(pack, "rid binary, spans binary")


def row_id(*parts: Column) -> Column:
    """A hash that tells rows apart: each part with its length, a null as itself. Rows equal in all parts share it."""
    marked = [F.coalesce(F.concat(F.length(p).cast("string"), F.lit(":"), p), F.lit("-")) for p in parts]
    return F.unhex(F.md5(F.concat(*marked).cast("binary")))


def removed_spans(docs: DataFrame, key: str = "doc_id", text: str = "text", length: int = 200, listed: int = LISTED) -> tuple[DataFrame, Column]:
    """(spans: rid, spans; the expression that gives a row's rid)."""
    rid = row_id(docs[key].cast("string"), docs[text])
    repeated = anchors(docs, text, length).groupBy("h").agg(F.sum("n").alias("n")).filter("n > 1")
    repeated = workspace.store(repeated, "anchors")
    found = workspace.store(contexts(docs, text, length, rid, repeated, listed), "contexts")
    same = workspace.store(repeated_runs(found, length), "runs")
    return workspace.store(spans(found, same, length), "spans"), rid


def remove_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", length: int = 200, listed: int = LISTED, span_bytes: int = SPAN_BYTES, with_kept: bool = False) -> DataFrame:
    """key, n_bytes, n_removed, n_spans, kept_sha256 (and the kept bytes) of each row."""
    spark = docs.sparkSession
    found, rid = removed_spans(docs, key, text, length, listed)
    size = found.agg(F.coalesce(F.sum(F.length("spans") + 64), F.lit(0))).first()[0]
    kind = docs.schema[key].dataType.simpleString()
    rows = docs.select(docs[key], F.coalesce(docs[text], F.lit("")).alias("t"), rid.alias("rid"))
    known = None
    if size <= span_bytes:
        known = spark.sparkContext.broadcast({r["rid"]: r["spans"] for r in found.toArrow().to_pylist()})
        rows = rows.withColumn("spans", F.lit(None).cast("binary"))
    else:
        rows = rows.join(found, "rid", "left").select(key, "t", "rid", "spans")

    def apply(batches):
        for b in lean(batches):
            out = []
            for t, r, s in zip(*(b.column(c).to_pylist() for c in ("t", "rid", "spans")), strict=True):
                raw = t.encode()
                s = known.value.get(bytes(r)) if known is not None else s
                gone, count, kept = 0, 0, raw
                if s:
                    own = np.frombuffer(s, np.int64).reshape(-1, 2)
                    gone, count = int((own[:, 1] - own[:, 0]).sum()), len(own)
                    at = [0, *own.ravel().tolist(), len(raw)]
                    kept = b"".join(raw[a:z] for a, z in zip(at[::2], at[1::2], strict=True))
                out.append((len(raw), gone, count, hashlib.sha256(kept).hexdigest(), *((kept,) if with_kept else ())))
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
            cols = list(zip(*out, strict=True)) or [()] * (5 if with_kept else 4)
            names = ["n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"][: len(cols)]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=False))], names=[key, *names])

    schema = f"`{key}` {kind}, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept binary" if with_kept else "")
    return rows.mapInArrow(apply, schema)
