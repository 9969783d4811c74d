"""N-gram Jaccard self-join in the Jaccard metric space: regions, pivots, windows, recursion.

Documents are sets of word shingles (64-bit hashes), the distance is 1 - Jaccard, which is a metric.
Equal sets are one node. Shingle sets of a corpus are so sparse that the distance to any fixed pivot
is 1 for nearly all nodes, where the triangle inequality excludes nothing; so the space is first cut
into regions in which distances differ: of two nodes within the radius, the larger (n shingles) must
have one of its first n - ceil(t n) + 1 shingles, in any fixed order of all shingles, among the first
m - ceil(2 t m / (1 + t)) + 1 of the smaller (m shingles, its core). Each such shared shingle is a region,
if it is in the core of a member; smaller members without it in theirs are left out. The order is by
hash with the most frequent shingles last, so that common passages open no regions.

1. Each region has a first pivot, and every member's distance to it is worked out (linear in the
   region's size). Members within the radius of it are linked to it. Regions whose members are all
   in one class by then are settled.
2. In open regions of at most ``LEAF`` members two others can be within the radius of each other only if
   their distances to the pivot differ by no more than it (triangle inequality) and their sizes
   allow it; what these windows leave across classes is compared.
3. Larger open regions that share members become one, and get several pivots. Every member's
   distances to them are worked out, and it goes to the Voronoi cell of the nearest. By the triangle
   inequality a partner of a member with nearest pivot p can lie in the cell of q only if the member's
   distances to q and p differ by at most two radii: within that window it is replicated to the
   cell of q. Members farther than ``FAR`` radii from all pivots, and those within one radius of
   that border, form the cell of the rest. Open cells are regions again, and are joined in the same way;
   those of at most ``CELL`` members in one task each. A region whose cells with their replicas would
   be no less work than itself (distances all alike) is joined in blocks by set size instead.

The rows of step 2 are at most LEAF / 2 for each member of a region; step 3 makes none for pairs. The
classes, connected components of the links, are exact.

Defined results: texts without words and null texts are empty sets, linked with nothing; fewer
words than a shingle form one shingle; rows with equal sets are in one class; a null key stands
in no result of a minimum; extra columns are not read; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.llm.common import Rolling, lean, mix, text_bytes
from fsmeta.llm.components import components
from fsmeta.llm.mixing import running
from fsmeta.plans import workspace

PIECE = 1 << 19
#: The rank table has 2^SLOTS bytes and takes at most TABLE shingles. ZONE: percent of a set's shingles, by hash, that are counted.
SLOTS, TABLE, ZONE = 24, 4_000_000, 60
#: Members of a region whose windows are looked at as rows; members that one task joins; pivots of a larger region;
#: radii within which a pivot has a cell.
LEAF, CELL, PIVOTS, FAR = 48, 512, 16, 2
#: The cells of a region must need less than SHRINK of its comparisons, else (or deeper than LEVELS) it is joined in blocks of BLOCK nodes.
SHRINK, LEVELS, BLOCK = 0.5, 12, 512
#: Rows of one group that a task reads at most, about; groups with more are dealt in parts.
PART = 512
#: Nodes whose texts are fetched by a broadcast list (8 bytes each) at most; more are fetched by a shuffle join.
LISTED = 2_000_000


def _case() -> np.ndarray:
    t = np.arange(256, dtype=np.uint8)
    t[0x41:0x5B] += 0x20
    return t


LOWER = _case()
GAPS = np.zeros(256, bool)
GAPS[[0x20, *range(0x09, 0x0E)]] = True


def _word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of texts laid end to end, and the n + 1 offsets of the texts in them."""
    inside = ~GAPS[data]
    cut = np.zeros(len(data) + 1, bool)
    cut[offsets] = True
    before = np.concatenate([[False], inside[:-1]])
    starts = np.flatnonzero(inside & (~before | cut[:-1]))
    after = np.concatenate([inside[1:], [False]])
    ends = np.flatnonzero(inside & (~after | cut[1:])) + 1
    return Rolling(data).ranges(starts, ends), np.searchsorted(starts, offsets)


def words_of(data: np.ndarray, offsets: np.ndarray):
    """(first text, word hashes, offsets) for runs of texts of bounded bytes; a long text is cut at gaps."""
    lo = 0
    while lo < len(offsets) - 1:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + PIECE, "right")) - 1)
        own = LOWER[data[offsets[lo] : offsets[hi]]]
        if hi == lo + 1 and len(own) > PIECE:
            at, parts = 0, []
            while at < len(own):
                end = min(len(own), at + PIECE)
                gap = np.flatnonzero(GAPS[own[end:]]) if end < len(own) else np.zeros(0, int)
                end = end + int(gap[0]) if len(gap) else len(own)
                parts.append(_word_hashes(own[at:end], np.array([0, end - at]))[0])
                at = end
            hashes = np.concatenate(parts)
            yield lo, hashes, np.array([0, len(hashes)])
        else:
            yield lo, *_word_hashes(own, offsets[lo : hi + 1] - offsets[lo])
        lo = hi


def _fold(parts: list[np.ndarray]) -> np.ndarray:
    total = np.zeros(len(parts[0]), np.uint64)
    for h in parts:
        total = (total + h) * np.uint64(0xD6E8FEB86659FD93)
        total ^= total >> np.uint64(29)
    return mix(total)


def sets_of(column: pa.Array, span: int):
    """Sorted distinct shingle hashes of each text, in order."""
    data, offsets = text_bytes(column)
    for _, h, at in words_of(data, offsets):
        n = max(0, len(h) - span + 1)
        folded = _fold([h[j : j + n] for j in range(span)]) if n else h[:0]
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            if b - a >= span:
                yield np.unique(folded[a : b - span + 1])
            elif b > a:
                yield _fold([h[i : i + 1] for i in range(a, b)])
            else:
                yield h[:0]


def node_of(s: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(s.tobytes(), digest_size=8).digest(), "little", signed=True)


def identity(s: np.ndarray) -> np.ndarray:
    """The leading 42 bits of a shingle: what regions are told apart by (a clash only adds a candidate)."""
    return s >> np.uint64(22)


def slot_of(ident: np.ndarray) -> np.ndarray:
    return ((ident * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - SLOTS)).astype(np.int64)


def core(n: int, percent: int) -> int:
    """How many first shingles of a set of n any larger (or equal) partner has one of."""
    return n + (-2 * percent * n // (100 + percent)) + 1


def first_shingles(s: np.ndarray, ranks: np.ndarray, percent: int) -> np.ndarray:
    """The shingles one of which any partner of the set shares, in the order that puts rarer ones first."""
    n = len(s)
    p = n + (-percent * n // 100) + 1
    return s[np.argsort(ranks[slot_of(identity(s))], kind="stable")][:p]


def _packed(s: list, nodes: list, sizes: list, bits: int):
    """Record batch of bucket, shingles, nodes, sizes; entries are sorted by shingle."""
    flat = np.concatenate(s)
    order = np.argsort(flat)
    flat = flat[order]
    bucket = (flat >> np.uint64(64 - bits)).astype(np.int32)
    short = identity(flat).astype(np.uint32)
    own, start = np.unique(bucket, return_index=True)
    cut = list(zip(start.tolist(), [*start[1:].tolist(), len(flat)], strict=True))
    columns = {"bucket": pa.array(own), "s": pa.array([short[a:b].tobytes() for a, b in cut], pa.binary())}
    if nodes:
        who = np.repeat(np.array(nodes, np.int64), [len(x) for x in s])
        for name, values in (("nodes", who[order]), ("sizes", np.concatenate(sizes)[order])):
            columns[name] = pa.array([values[a:b].tobytes() for a, b in cut], pa.binary())
    return pa.RecordBatch.from_pydict(columns)


def overlap(n: int, percent: int) -> int:
    """What a set of n shares at least with any partner."""
    return -(-percent * n // 100)


def shipped(n: int, percent: int) -> int:
    """How many shared first shingles a set of n can be held to: it shows n - overlap + this many."""
    return max(1, min(n // 5, overlap(n, percent)))


def needed(n: int, percent: int) -> int:
    """How many of its first shingles a set of n shares if it has a partner: as many as the smallest
    set that can be one is held to."""
    return shipped(overlap(n, percent), percent)


def crowded(docs: DataFrame, rows: DataFrame, text: str, span: int, percent: int, bits: int) -> DataFrame:
    """node: the nodes that can have a partner at all.

    Two sets within the radius share at least k of their first n - ceil(t n) + k shingles by hash, for
    any k up to what they share at all. A set shows as many shingles as its own k asks for (it rises
    with n), and must find as many in other nodes as the k of its smallest possible partner; those
    that don't are alone. An entry is one number: 24 bits of the shingle (beyond its bucket) and 40
    of the node. Clashes of shingles only let a node stay.
    """
    low = (1 << 40) - 1

    def pack(batches):
        seen, held, size = set(), [], 0
        for b in batches:
            for s in sets_of(b.column(0), span):
                n = len(s)
                if not n or (node := node_of(s)) in seen:
                    continue
                seen.add(node)
                first = s[: n - overlap(n, percent) + shipped(n, percent)]
                held.append((first, np.full(len(first), node & low, np.uint64)))
                size += len(first)
                if size > 1_500_000:
                    yield ship(held)
                    held, size = [], 0
        if held:
            yield ship(held)

    def ship(held):
        s, who = (np.concatenate(x) for x in zip(*held, strict=True))
        bucket = (s >> np.uint64(64 - bits)).astype(np.int32)
        entry = (((s >> np.uint64(40 - bits)) & np.uint64((1 << 24) - 1)) << np.uint64(40)) | who
        order = np.argsort(bucket, kind="stable")
        own, start = np.unique(bucket[order], return_index=True)
        entry = entry[order]
        return pa.RecordBatch.from_arrays([pa.array(own), pa.array([entry[a:z].tobytes() for a, z in zip(start.tolist(), [*start[1:].tolist(), len(entry)], strict=True)], pa.binary())], names=["bucket", "e"])

    slices = max(64, 1 << (bits - 4))

    def count(batches):
        held, size = [], 0

        def out():
            who, n = np.unique(np.concatenate(held), return_counts=True)
            part = (who % np.uint64(slices)).astype(np.int32)
            order = np.argsort(part, kind="stable")
            own, start = np.unique(part[order], return_index=True)
            cut = list(zip(start.tolist(), [*start[1:].tolist(), len(part)], strict=True))
            who, n = who[order].astype(np.int64), n[order].astype(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(own), *(pa.array([x[a:z].tobytes() for a, z in cut], pa.binary()) for x in (who, n))], names=["bucket", "who", "hits"])

        for g in by_bucket(batches):
            e = np.unique(np.concatenate([np.frombuffer(x, np.uint64) for x in g["e"]]))
            s = e >> np.uint64(40)
            same = np.zeros(len(e) + 1, bool)
            same[1:-1] = s[1:] == s[:-1]
            held.append((e & np.uint64(low))[same[:-1] | same[1:]])
            size += len(held[-1])
            if size > 2_000_000:
                yield out()
                held, size = [], 0
        if size:
            yield out()

    def add_up(batches):
        for g in by_bucket(batches):
            who, at = np.unique(np.concatenate([np.frombuffer(x, np.int64) for x in g["who"]]), return_inverse=True)
            hits = np.bincount(at, np.concatenate([np.frombuffer(x, np.int64) for x in g["hits"]])).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(who), pa.array(hits)], names=["who", "hits"])

    packed = docs.select(text).mapInArrow(pack, "bucket int, e binary")
    counted = _grouped(packed).mapInArrow(count, "bucket int, who binary, hits binary")
    hits = _grouped(counted).mapInArrow(add_up, "who long, hits long")
    nodes = rows.groupBy("node").agg(F.first("n_shingles").alias("n")).withColumn("who", F.col("node").bitwiseAND(F.lit(low)))
    least = F.ceil(F.lit(percent) * F.col("n") / 100)
    least = F.greatest(F.lit(1), F.least(F.floor(least / 5), F.ceil(F.lit(percent) * least / 100)))
    return nodes.join(hits, "who").filter(F.col("hits") >= least).select("node", "n")


def entries(texts: DataFrame, span: int, percent: int, bits: int, ranks: np.ndarray | None) -> DataFrame:
    """bucket, s, nodes, sizes: packed first shingles of every node, told apart by 42 bits. ``texts``: node, t.

    Without ``ranks`` it is for counting: no nodes, and so many shingles by hash as can come
    first once frequent ones have moved last (as a rule; more would cost only speed).
    """
    shared = texts.sparkSession.sparkContext.broadcast(ranks)

    def pack(batches):
        own = shared.value
        sets, nodes, sizes, held = [], [], [], 0
        for b in lean(batches):
            for node, s in zip(b.column(0).to_pylist(), sets_of(b.column(1), span), strict=True):
                first = s[: len(s) * ZONE // 100 + 1] if own is None else first_shingles(s, own, percent)
                sets.append(first)
                if own is not None:
                    nodes.append(node)
                    # negative where the shingle is not in the set's core
                    sizes.append(np.where(np.arange(len(first)) < core(len(s), percent), len(s), -len(s)).astype(np.int32))
                held += len(first)
                if held > 1_500_000:
                    yield _packed(sets, nodes, sizes, bits)
                    sets, nodes, sizes, held = [], [], [], 0
        if sets:
            yield _packed(sets, nodes, sizes, bits)

    return texts.select("node", "t").mapInArrow(pack, "bucket int, s binary" + ("" if ranks is None else ", nodes binary, sizes binary"))


def by_bucket(batches):
    """Columns of all rows of each bucket, from rows sorted by bucket."""
    now, held = None, []
    for b in lean(batches):
        names = b.schema.names
        for row in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if row[0] != now and held:
                yield {n: [r[i] for r in held] for i, n in enumerate(names)}
                held = []
            now = row[0]
            held.append(row)
    if held:
        yield {n: [r[i] for r in held] for i, n in enumerate(names)}


def _grouped(packed: DataFrame) -> DataFrame:
    return packed.repartition("bucket").sortWithinPartitions("bucket")


def rank_table(texts: DataFrame, span: int, percent: int, bits: int) -> np.ndarray:
    """Logarithmic frequency of shingles, by slot: 0 for one node, 1 for two or three, and so on.

    The table has 2^SLOTS entries whatever the input; at most ``TABLE`` shingles enter it, the most
    frequent (where there are more, the threshold rises). It only fixes an order that all
    tasks share, so clashes and what it lacks change speed, not results.
    """

    def count(batches):
        for g in by_bucket(batches):
            s, n = np.unique(np.concatenate([np.frombuffer(x, np.uint32) for x in g["s"]]), return_counts=True)
            many = n > 1
            if many.any():
                rank = np.minimum(np.log2(n[many]).astype(np.uint8), 40)
                yield pa.RecordBatch.from_arrays([pa.array([g["bucket"][0]], pa.int32()), pa.array([s[many].tobytes()], pa.binary()), pa.array([rank.tobytes()], pa.binary())], names=["bucket", "s", "rank"])

    packed = entries(texts, span, percent, bits, None)
    counted = workspace.store(_grouped(packed).mapInArrow(count, "bucket int, s binary, rank binary"), "ranks")

    def spread(batches):
        for b in lean(batches):
            r, many = np.unique(np.frombuffer(b"".join(b.column("rank").to_pylist()), np.uint8), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(r.astype(np.int64)), pa.array(many.astype(np.int64))], names=["r", "many"])

    least, total = 41, 0
    for r in counted.mapInArrow(spread, "r long, many long").groupBy("r").agg(F.sum("many").alias("many")).orderBy(F.desc("r")).collect():  # 41 rows at most
        if total + r["many"] > TABLE:
            break
        least, total = r["r"], total + r["many"]

    def pick(batches):
        for b in lean(batches):
            for k, s, r in zip(*(c.to_pylist() for c in b.columns), strict=True):
                r = np.frombuffer(r, np.uint8)
                own, r = np.frombuffer(s, np.uint32)[r >= least], r[r >= least]
                if len(own):
                    ident = (np.uint64(k) << np.uint64(42 - bits)) | (own.astype(np.uint64) & np.uint64((1 << (42 - bits)) - 1))
                    yield pa.RecordBatch.from_arrays([pa.array([slot_of(ident).astype(np.uint32).tobytes()], pa.binary()), pa.array([r.tobytes()], pa.binary())], names=["slots", "r"])

    table = np.zeros(1 << SLOTS, np.uint8)
    if total:
        for row in counted.mapInArrow(pick, "slots binary, r binary").toLocalIterator():
            slots = np.frombuffer(row["slots"], np.uint32)
            np.maximum.at(table, slots, np.frombuffer(row["r"], np.uint8))
    return table


def regions(packed: DataFrame, run: int = 1 << 15) -> DataFrame:
    """s, pivot, np, nodes, sizes: members (packed, in runs) of every region of two nodes or more; the pivot is
    the least of them. Regions with the same members and cores are the same region: ``s`` is a hash of them."""

    def gather(batches):
        for g in by_bucket(batches):
            s, who, n = (np.concatenate([np.frombuffer(x, t) for x in g[c]]) for c, t in (("s", np.uint32), ("nodes", np.int64), ("sizes", np.int32)))
            order = np.lexsort((who, s))
            s, who, n = s[order], who[order], n[order]
            new = np.ones(len(s), bool)
            new[1:] = (s[1:] != s[:-1]) | (who[1:] != who[:-1])
            s, who, n = s[new], who[new], n[new]
            start = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
            size = np.diff(np.append(start, len(s)))
            out = []
            for a, m in zip(start[size > 1].tolist(), size[size > 1].tolist(), strict=True):
                own, size_ = who[a : a + m], n[a : a + m]
                if (size_ < 0).all():
                    continue
                keep = np.abs(size_) >= size_[size_ > 0].min()
                own, size_ = own[keep], size_[keep]
                if len(own) > 1:
                    key = node_of(np.concatenate([own, size_.astype(np.int64)]))
                    out += [(key, int(own[0]), int(abs(size_[0])), own[c : c + run].tobytes(), size_[c : c + run].tobytes()) for c in range(0, len(own), run)]
            out = list(dict.fromkeys(out))
            if out:
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=["s", "pivot", "np", "nodes", "sizes"])

    return _grouped(packed).mapInArrow(gather, "s long, pivot long, np long, nodes binary, sizes binary").distinct()


def members(found: DataFrame) -> DataFrame:
    """s, pivot, np, node, n, inner: one row a member, with the sizes of both sets and whether its core has the shingle."""

    def spread(batches):
        for b in lean(batches):
            for s, p, m, raw, sizes in zip(*(c.to_pylist() for c in b.columns), strict=True):
                who = np.frombuffer(raw, np.int64)
                n = np.frombuffer(sizes, np.int32).astype(np.int64)
                cols = [np.full(len(who), s), np.full(len(who), p), np.full(len(who), m), who, np.abs(n)]
                yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols), pa.array(n > 0)], names=["s", "pivot", "np", "node", "n", "inner"])

    return found.mapInArrow(spread, "s long, pivot long, np long, node long, n long, inner boolean")


def texts_of(docs: DataFrame, nodes: DataFrame, text: str, span: int) -> DataFrame:
    """node, t: one text of each listed node."""
    spark = docs.sparkSession
    listed = nodes.limit(LISTED + 1).toArrow()["node"].to_numpy()
    few = len(listed) <= LISTED
    shared = spark.sparkContext.broadcast(np.sort(listed) if few else None)

    def pick(batches):
        want, seen = shared.value, set()
        for b in lean(batches):
            keys = np.array([node_of(s) if len(s) else 0 for s in sets_of(b.column(0), span)], np.int64)
            if want is not None:
                at = np.minimum(np.searchsorted(want, keys), max(0, len(want) - 1))
                take = np.flatnonzero(want[at] == keys).tolist() if len(want) else []
            else:
                take = range(len(keys))
            new = []
            for i in take:
                if (k := int(keys[i])) not in seen:
                    seen.add(k)
                    new.append(i)
            if new:
                yield pa.RecordBatch.from_arrays([pa.array(keys[new]), b.column(0).take(pa.array(new))], names=["node", "t"])

    picked = docs.select(F.coalesce(docs[text], F.lit("")).alias(text)).mapInArrow(pick, "node long, t string")
    picked = picked if few else picked.join(nodes, "node", "left_semi")
    return picked.groupBy("node").agg(F.first("t").alias("t"))


def common(x: np.ndarray, y: np.ndarray) -> int:
    at = np.minimum(np.searchsorted(x, y), len(x) - 1)
    return int((x[at] == y).sum())


def within(shared, na, nb, percent: int):
    return 100 * shared >= percent * (na + nb - shared)


LINK = "a long, b long, na long, nb long, shared long"


def link_batch(rows: list) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [()] * 5
    return pa.RecordBatch.from_arrays([pa.array(list(map(int, c)), pa.int64()) for c in cols], names=["a", "b", "na", "nb", "shared"])


def star_distances(pairs: DataFrame, t: DataFrame, span: int) -> DataFrame:
    """Set sizes and intersections of pairs of a pivot and a node (a, b). ``t``: node, t.

    Nodes are dealt by pivot, those of one that has many in parts; the pivot's text goes to each part once.
    """
    parts = F.ceil(F.col("n") / PART).cast("int")
    pivots = pairs.groupBy("a").agg(F.count("*").alias("n")).select("a", parts.alias("parts"))
    many = pivots.filter("parts > 1")
    part = F.pmod(F.xxhash64("b"), F.coalesce("parts", F.lit(1))).cast("int")
    right = pairs.join(many, "a", "left").select("a", part.alias("part"), F.lit(1).alias("kind"), F.col("b").alias("node"))
    left = pivots.select("a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("kind"), F.col("a").alias("node"))
    rows = left.unionByName(right).join(t, "node").select("a", "part", "kind", "node", "t")

    def compare(batches):
        pivot, first = None, None
        for b in lean(batches):
            out = []
            for a, kind, node, s in zip(*(b.column(c).to_pylist() for c in ("a", "kind", "node")), sets_of(b.column("t"), span), strict=True):
                if not kind:
                    pivot, first = a, s
                    continue
                if pivot != a:
                    raise ValueError("a group without its pivot")
                out.append((a, node, len(first), len(s), common(first, s)))
            if out:
                yield link_batch(out)

    return rows.repartition("a", "part").sortWithinPartitions("a", "part", "kind").mapInArrow(compare, LINK)


def joined(sets: list, nodes: list, labels: list, percent: int) -> list:
    """Links among nodes of different classes, one for each two classes that meet (they join there and then)."""
    n, shared, out = np.array([len(x) for x in sets]), intersections(sets, sets), []
    lab = np.array(labels)
    ok = np.triu(within(shared, n[:, None], n[None, :], percent) & (lab[:, None] != lab[None, :]), 1)
    at, up = np.argwhere(ok).tolist(), {}
    for i, j in at:
        a, b = root(up, labels[i]), root(up, labels[j])
        if a != b:
            up[a] = b
            out.append((nodes[i], nodes[j], n[i], n[j], shared[i, j]))
    return out


def root(up: dict, x: int) -> int:
    while (y := up.get(x, x)) != x:
        up[x] = x = up.get(y, y)
    return x


def leaf_links(cells: DataFrame, t: DataFrame, span: int, percent: int) -> DataFrame:
    """Links between classes inside small regions (rows: cell, node, label)."""

    def solve(batches):
        now, sets, nodes, labels, out = None, [], [], [], []
        for b in lean(batches):
            for cell, node, label, s in zip(*(b.column(c).to_pylist() for c in ("cell", "node", "label")), sets_of(b.column("t"), span), strict=True):
                if cell != now and sets:
                    out += joined(sets, nodes, labels, percent)
                    sets, nodes, labels = [], [], []
                now = cell
                sets.append(s)
                nodes.append(node)
                labels.append(label)
            if out:
                yield link_batch(out)
                out = []
        if sets and (out := joined(sets, nodes, labels, percent)):
            yield link_batch(out)

    rows = cells.select("cell", "node", "label").join(t, "node").select("cell", "node", "label", "t")
    return rows.repartition("cell").sortWithinPartitions("cell").mapInArrow(solve, LINK)


def voronoi(cells: DataFrame, t: DataFrame, span: int, percent: int, level: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(links of members to pivots; the Voronoi cells of each region with replicas: cell, node, n, up (the region);
    the regions whose cells are not worth it). Rows: cell, node, n, label, members."""
    parts = F.ceil(F.col("members") / PART).cast("int")
    q = F.pmod(F.xxhash64("node", F.lit(level)), F.lit(PIVOTS))
    pivots = cells.groupBy("cell", q.alias("q")).agg(F.min_by(F.struct("node", "n", "label", "members"), F.xxhash64(F.lit(level), "node")).alias("p")).select("cell", "p.*")
    left = pivots.select("cell", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part"), F.lit(0).alias("kind"), "node", "n", "label", "members")
    right = cells.select("cell", F.pmod(F.xxhash64("node"), parts).cast("int").alias("part"), F.lit(1).alias("kind"), "node", "n", "label", "members")
    rows = left.unionByName(right).join(t, "node").select("cell", "part", "kind", "node", "n", "label", "members", "t")
    radius = 1 - percent / 100 + 1e-9
    kinds = "cell long, node long, n long, up long, members long, a long, b long, na long, nb long, shared long"
    names = kinds.replace(",", "").split()[0::2]

    def settle(batches):
        now, own = None, []
        for b in lean(batches):
            out = []
            for cell, part, kind, node, n, label, size, s in zip(*(b.column(c).to_pylist() for c in ("cell", "part", "kind", "node", "n", "label", "members")), sets_of(b.column("t"), span), strict=True):
                if (cell, part) != now:
                    now, own = (cell, part), []
                if not kind:
                    own.append((node, label, s))
                    continue
                far = []
                for p, other, ps in own:
                    shared = common(ps, s)
                    far.append(1 - shared / (len(ps) + len(s) - shared))
                    if label != other and within(shared, len(ps), len(s), percent):
                        out.append((None, None, None, None, None, p, node, len(ps), len(s), shared))
                least = min(far)
                into = [own[j][0] for j, d in enumerate(far) if d - least <= 2 * radius] if least <= FAR * radius else []
                into += [None] if least > (FAR - 1) * radius else []
                out += [(cell_id(cell, p), node, n, cell, size, None, None, None, None, None) for p in into]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=names)

    done = rows.repartition("cell", "part").sortWithinPartitions("cell", "part", "kind", "node").mapInArrow(settle, kinds)
    done = workspace.store(done, "cells")
    below = done.filter("a is null")
    work = below.groupBy("up", "cell").agg(F.count("*").cast("double").alias("m"), F.max("members").cast("double").alias("of")).groupBy("up").agg(F.sum(F.col("m") * F.col("m")).alias("work"), F.max("of").alias("of"))
    costly = workspace.store(work.filter(F.col("work") > SHRINK * F.col("of") * F.col("of")).select(F.col("up").alias("cell")), "costly")
    return done.filter("a is not null").select("a", "b", "na", "nb", "shared"), below.select("cell", "node", "n", "up"), costly


def cell_id(cell: int, pivot: int | None) -> int:
    return int.from_bytes(hashlib.blake2b(f"{cell}/{pivot}".encode(), digest_size=8).digest(), "little", signed=True)


def block_links(cells: DataFrame, t: DataFrame, span: int, percent: int) -> DataFrame:
    """Links between classes inside large cells whose distances are all alike (rows: cell, node, label, n).

    The nodes of a class with many members in the cell form blocks of their own, all others mixed ones, both in
    the order of set sizes. A pair of blocks goes to one task if the sizes of some two of their nodes are
    alike, unless both are of one class, and gives only links that join classes not yet joined there.
    """
    big = cells.groupBy("cell", "label").agg(F.count("*").alias("_m")).filter(F.col("_m") >= BLOCK).select("cell", "label", F.col("label").alias("own"))
    grouped = cells.join(big, ["cell", "label"], "left").withColumn("side", F.xxhash64("cell", "own", F.col("own").isNull()))
    spot = F.col("n") * 64 + F.shiftrightunsigned(F.xxhash64("node"), 58)
    rows = running(grouped.select("cell", "side", "own", "node", "label", "n", F.lit(1).alias("one")), "side", spot, ["node"], "one")
    block = F.xxhash64("side", F.floor(F.col("before") / BLOCK))
    rows = workspace.store(rows.select("cell", "own", "node", "label", "n", block.alias("block")), "blocks")
    ends = rows.groupBy("cell", "block").agg(F.min("n").alias("low"), F.max("n").alias("high"), F.max("own").alias("own"))
    other = ends.select("cell", *[F.col(c).alias(c + "2") for c in ("block", "low", "high", "own")])
    sizes = (100 * F.col("high") >= percent * F.col("low2")) & (100 * F.col("high2") >= percent * F.col("low"))
    apart = ~F.coalesce(F.col("own") == F.col("own2"), F.lit(False))
    pairs = ends.join(other, "cell").filter((F.col("block") <= F.col("block2")) & sizes & apart)
    pairs = pairs.select("cell", F.col("block").alias("i"), F.col("block2").alias("j"))
    sides = pairs.select("*", F.explode(F.array_distinct(F.array("i", "j"))).alias("block"))
    sent = rows.join(sides, ["cell", "block"]).join(t, "node").select("cell", "i", "j", "block", "node", "label", "t")

    def compare(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        sets = [s for c in table["t"].chunks for s in sets_of(c, span)]
        nodes, labels, block = (table[c].to_pylist() for c in ("node", "label", "block"))
        i, j = table["i"][0].as_py(), table["j"][0].as_py()
        left, right = ([k for k, b in enumerate(block) if b == side] for side in (i, j))
        shared = intersections([sets[k] for k in left], [sets[k] for k in right])
        na, nb = (np.array([len(sets[k]) for k in side]) for side in (left, right))
        out, up = [], {}
        la, lb = (np.array([labels[k] for k in side]) for side in (left, right))
        for a, b in np.argwhere(within(shared, na[:, None], nb[None, :], percent) & (la[:, None] != lb[None, :])).tolist():
            ra, rb = root(up, labels[left[a]]), root(up, labels[right[b]])
            if ra != rb:
                up[ra] = rb
                out.append((nodes[left[a]], nodes[right[b]], na[a], nb[b], shared[a, b]))
        return pa.Table.from_batches([link_batch(out)])

    return sent.groupBy("cell", "i", "j").applyInArrow(compare, LINK)


def intersections(left: list[np.ndarray], right: list[np.ndarray], step: int = 4_000_000) -> np.ndarray:
    """Sizes of all intersections of two lists of sets, by meeting equal elements in sorted order."""
    out = np.zeros(len(left) * len(right), np.int64)
    x, y = np.concatenate(left), np.concatenate(right)
    xi, yi = (np.repeat(np.arange(len(side)), [len(s) for s in side]) for side in (left, right))
    order = np.argsort(y)
    y, yi = y[order], yi[order]
    lo, hi = np.searchsorted(y, x, "left"), np.searchsorted(y, x, "right")
    n = hi - lo
    upto = np.cumsum(n)
    at = 0
    while at < len(x):
        end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + step, "right")))
        m = n[at:end]
        total = int(m.sum())
        if total:
            place = np.arange(total) - np.repeat(np.cumsum(m) - m, m) + np.repeat(lo[at:end], m)
            out += np.bincount(np.repeat(xi[at:end], m) * len(right) + yi[place], minlength=len(out))
        at = end
    return out.reshape(len(left), len(right))


def alike(x, y, percent: int):
    """Sets within the radius have sizes like that."""
    return 100 * F.least(x, y) >= percent * F.greatest(x, y)


def distances_to_pivots(own: DataFrame, texts: DataFrame, span: int, percent: int) -> DataFrame:
    """Of all members to the pivots of their regions, where sizes allow a link."""
    pairs = own.filter((F.col("node") != F.col("pivot")) & alike("n", "np", percent)).select(F.col("pivot").alias("a"), F.col("node").alias("b")).distinct()
    return workspace.store(star_distances(workspace.store(pairs, "pairs"), texts, span), "distances")


def still_open(cells: DataFrame, label: DataFrame) -> DataFrame:
    """The rows of regions whose members are not all in one class, with label and members."""
    now = cells.join(label, "node", "left").withColumn("label", F.coalesce("label", "node"))
    still = now.groupBy("cell").agg(F.count("*").alias("members"), F.min("label").alias("_lo"), F.max("label").alias("_hi")).filter("_lo <> _hi").select("cell", "members")
    return now.join(still, "cell")


def windowed_pairs(rows: DataFrame, known: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of members of small regions that neither classes, sizes nor distances to the pivot exclude."""
    gap = known.select(F.col("a").alias("pivot"), F.col("b").alias("node"), (1 - F.col("shared") / (F.col("na") + F.col("nb") - F.col("shared"))).alias("_d"))
    # all distances to the pivot itself are known
    rest = rows.filter("node <> pivot").join(gap, ["pivot", "node"], "left")
    rest = rest.select("cell", "node", "label", "n", "inner", F.coalesce("_d", 1 - F.least("n", "np") / F.greatest("n", "np")).alias("lo"), F.coalesce("_d", F.lit(1.0)).alias("hi"))
    x, y = (rest.select(*[F.col(c).alias(c + e) for c in rest.columns]) for e in "xy")
    radius = 1 - percent / 100 + 1e-9
    window = (F.col("lox") - F.col("hiy") <= radius) & (F.col("loy") - F.col("hix") <= radius)
    # the shingle is in the core of the smaller
    window &= (F.col("innerx") & (F.col("nx") <= F.col("ny"))) | (F.col("innery") & (F.col("ny") <= F.col("nx")))
    may = (F.col("cellx") == F.col("celly")) & (F.col("nodex") < F.col("nodey")) & (F.col("labelx") != F.col("labely")) & alike("nx", "ny", percent) & window
    return x.join(y, may).select(F.col("nodex").alias("a"), F.col("nodey").alias("b")).distinct()


def crowds(rows: DataFrame) -> DataFrame:
    """cell, node, n: large open regions, those that share members as one."""
    rows = workspace.store(rows.select("cell", "node", "n"), "large")
    edges = rows.select(F.concat(F.lit("r"), "cell").alias("a"), F.concat(F.lit("n"), "node").alias("b"))
    own = components(edges).filter(F.col("node").startswith("n")).select(F.substring("node", 2, 30).cast("long").alias("node"), F.xxhash64("label").alias("cell"))
    return workspace.store(rows.select("node", "n").distinct().join(own, "node").select("cell", "node", "n"), "crowds")


def classes(docs: DataFrame, key: str = "doc_id", text: str = "text", span: int = 5, percent: int = 75) -> tuple[DataFrame, DataFrame]:
    """(membership: the key, n_shingles, node, label for each row; links: a, b, na, nb, shared
    between nodes). Links connect each class; pairs already in one class are not tried again."""
    spark = docs.sparkSession
    bits = min(20, max(10, (4 * int(spark.conf.get("spark.sql.shuffle.partitions")) - 1).bit_length()))

    def describe(batches):
        for b in lean(batches):
            sets = [(len(s), node_of(s) if len(s) else None) for s in sets_of(b.column(1), span)]
            n, node = zip(*sets, strict=True) if sets else ((), ())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(node, pa.int64())], names=[key, "n_shingles", "node"])

    kind = docs.schema[key].dataType.simpleString()
    rows = workspace.store(docs.select(key, text).mapInArrow(describe, f"`{key}` {kind}, n_shingles long, node long"), "rows")
    # nodes that can have a partner, and one text of each
    sizes = workspace.store(crowded(docs, rows.filter("node is not null"), text, span, percent, bits), "candidates")
    texts = workspace.store(texts_of(docs, sizes.select("node"), text, span), "texts")
    found = regions(entries(texts, span, percent, bits, rank_table(texts, span, percent, bits)))
    own = workspace.store(members(found), "in_regions")

    near = within(F.col("shared"), F.col("na"), F.col("nb"), percent)
    known = distances_to_pivots(own, texts, span, percent)
    links = known.filter(near)
    label = components(links)
    open_rows = workspace.store(still_open(own.withColumnRenamed("s", "cell"), label), "open")
    small = windowed_pairs(open_rows.filter(F.col("members") <= LEAF), known, percent)
    links = links.unionByName(workspace.store(star_distances(workspace.store(small, "pairs"), texts, span).filter(near), "links"))
    cells = crowds(open_rows.filter(F.col("members") > LEAF))
    for level in range(LEVELS + 1):
        label = components(links)
        now = workspace.store(still_open(cells, label), "open")
        small = F.col("members") <= CELL
        kinds = now.agg(F.count(F.when(small, 1)), F.count(F.when(~small, 1))).first()
        if kinds[0]:
            links = links.unionByName(workspace.store(leaf_links(now.filter(small), texts, span, percent), "links"))
        if kinds[1]:
            wide = now.filter(~small)
            more, cells, costly = voronoi(wide, texts, span, percent, level)
            costly = costly if level < LEVELS else wide.select("cell").distinct()
            links = links.unionByName(more)
            # what the pivots have joined by now need not be compared in blocks
            left = workspace.store(still_open(wide.join(costly, "cell", "left_semi").select("cell", "node", "n"), components(links)), "open")
            links = links.unionByName(workspace.store(block_links(left, texts, span, percent), "links"))
            cells = cells.join(costly.withColumnRenamed("cell", "up"), "up", "left_anti").drop("up")
        if not kinds[1] or level == LEVELS:
            label = components(links) if kinds[0] or kinds[1] else label
            break
    member = rows.join(label, "node", "left").withColumn("label", F.coalesce("label", "node"))
    return member, links


def join_components(docs: DataFrame, key: str = "doc_id", text: str = "text", span: int = 5, percent: int = 75) -> DataFrame:
    """The key, n_shingles and component_id (least key reachable by links) of each row."""
    member, _ = classes(docs, key, text, span, percent)
    least = member.filter("label is not null").groupBy("label").agg(F.min(key).alias("component_id"))
    return member.join(least, "label", "left").select(key, "n_shingles", F.coalesce("component_id", key).alias("component_id"))
