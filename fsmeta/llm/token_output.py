"""Token-id output: sharded raw id files with a minimal perfect hash index for keyed access.

``write_tokens`` range-partitions the documents by key, encodes them and writes, per task,
shards of at most ``shard_ids`` ids: ``.ids`` holds the raw little-endian ids of all its
documents end to end, ``.idx`` the row table and the hash index with fingerprints.
``read_rows`` reads every shard back; ``lookup`` finds single keys in constant time.

Defined results: null text is an empty text (only the end id is stored); null keys are
stored first and not indexed; rows of equal keys are all stored, next to each other, those of different
texts in the order of the texts' hashes; extra columns are not read; an empty table gives no shard and no rows.
"""

from __future__ import annotations

import gc
import sys
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fsmeta.llm import pretokens
from fsmeta.llm.common import lean
from fsmeta.llm.store_ids import HEADER_SIZE, Replaced, ShardIndex, header, id_width, read_all, read_range
from fsmeta.plans import workspace

#: Array codes of 2 and 4 bytes.
KINDS = {2: "H", 4: "I"}
MANIFEST = "part int, seq int, ids_uri string, idx_uri string, min_key long, max_key long, n_docs long, n_ids long"


class Encoder:
    """Ids of whole texts by the tokenizers library, each pre-token encoded once per worker while it is kept.

    The table of pre-tokens is bounded and let go when full. Texts that are not plain go whole
    to the library.
    """

    def __init__(self, name: str, width: int, entries: int = 1_200_000, longest: int = 48):
        self.tok, self.name, self.width, self.entries, self.longest = pretokens.load(name), name, width, entries, longest
        self.special = pretokens.specials(self.tok)

    def raw(self, ids: list[int]) -> bytes:
        return array(KINDS[self.width], ids).tobytes() if sys.byteorder == "little" else np.array(ids, f"<u{self.width}").tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        """The collector of cycles rests meanwhile: many small objects come and go, none in a cycle."""
        was = gc.isenabled()
        gc.disable()
        try:
            return self._encode(texts)
        finally:
            if was:
                gc.enable()

    def _encode(self, texts: list[str]) -> list[bytes]:
        cache = pretokens.Cache.of(f"{self.name}/{self.width}", self.entries)
        out, split = [b""] * len(texts), [None] * len(texts)
        for i, text in enumerate(texts):
            if pretokens.plain(text, self.special):
                split[i] = pretokens.BYTE_LEVEL.findall(text)
            else:
                out[i] = self.raw(self.tok.encode(text, add_special_tokens=False).ids)
        missing, extra = pretokens.unknown(split, cache), {}
        for at in range(0, len(missing), 4096):
            part = missing[at : at + 4096]
            e = self.tok.encode(part, is_pretokenized=True, add_special_tokens=False)
            raw, cut = self.raw(e.ids), np.searchsorted(np.array(e.word_ids), np.arange(len(part) + 1)) * self.width
            for t, lo, hi in zip(part, cut.tolist(), cut[1:].tolist(), strict=False):
                (cache if len(t) <= self.longest else extra)[t] = raw[lo:hi]
        look = _Both(cache, extra) if extra else cache
        for i, s in enumerate(split):
            if s:
                out[i] = b"".join(map(look.__getitem__, s))
        return out


class _Both(dict):
    """A kept table, then what belongs to these texts alone."""

    def __init__(self, kept: dict, own: dict):
        super().__init__(own)
        self.kept = kept

    def __missing__(self, k: str):
        return self.kept[k]


def slices(texts: list[str], chars: int = 6_000_000):
    """Runs of texts of bounded size."""
    at, n = 0, 0
    for i, t in enumerate(texts):
        n += len(t)
        if n >= chars:
            yield at, i + 1
            at, n = i + 1, 0
    if at < len(texts):
        yield at, len(texts)


class _Shard:
    def __init__(self, uri: str, part: int, seq: int, width: int):
        self.part, self.seq, self.width, self.n_ids = part, seq, width, 0
        self.uri = f"{uri}/shard-{part:06d}-{seq:04d}"
        self.keys, self.lengths, self.chunks, self.held = [], [], [], 0
        self.file = Replaced(self.uri + ".ids")
        self.file.write(header(width))

    def add(self, key, ids: bytes) -> None:
        self.keys.append(key)
        self.lengths.append(len(ids) // self.width)
        self.n_ids += self.lengths[-1]
        self.chunks.append(ids)
        self.held += len(ids)
        if self.held > 1 << 20:
            self.flush()

    def flush(self) -> None:
        self.file.write(b"".join(self.chunks))
        self.chunks, self.held = [], 0

    def close(self) -> tuple:
        self.flush()
        self.file.close()
        has = np.array([k is not None for k in self.keys], bool)
        keys = np.array([0 if k is None else k for k in self.keys], np.int64)
        idx = Replaced(self.uri + ".idx")
        idx.write(ShardIndex.build(keys, has, np.array(self.lengths, np.int64)).dump())
        idx.close()
        known = keys[has]
        ends = (int(known.min()), int(known.max())) if len(known) else (None, None)
        return (self.part, self.seq, self.uri + ".ids", self.uri + ".idx", *ends, len(keys), self.n_ids)


def write_tokens(docs: DataFrame, uri: str, tokenizer: str = "byte_bpe_50k.json", end_id: int | None = 2, key: str = "doc_id", text: str = "text", shard_ids: int = 1 << 26, cache_entries: int = 1_200_000) -> DataFrame:
    """Write the shards under ``uri`` and return their manifest (also stored there). A worker keeps
    ``cache_entries`` pre-tokens at most (about 200 bytes each)."""
    spark, width = docs.sparkSession, 2 if pretokens.load(tokenizer).get_vocab_size() <= 1 << 16 else 4
    rows = docs.select(docs[key].cast("long").alias("k"), F.coalesce(docs[text], F.lit("")).alias("t"))
    rows = rows.repartitionByRange(F.col("k"), F.xxhash64("t")).sortWithinPartitions("k", F.xxhash64("t"))
    names = MANIFEST.replace(",", "").split()[0::2]

    def encode(batches):
        from pyspark import TaskContext

        part, enc, shard, seq, done = TaskContext.get().partitionId(), None, None, 0, []
        tail = b"" if end_id is None else np.array([end_id], f"<u{width}").tobytes()
        for b in lean(batches, 2048):
            enc = enc or Encoder(tokenizer, width, cache_entries)
            keys, texts = b.column(0).to_pylist(), b.column(1).to_pylist()
            for lo, hi in slices(texts):
                for k, ids in zip(keys[lo:hi], enc.encode(texts[lo:hi]), strict=True):
                    shard = shard or _Shard(uri, part, seq, width)
                    shard.add(k, ids + tail)
                    if shard.n_ids >= shard_ids:
                        done, shard, seq = [*done, shard.close()], None, seq + 1
        if shard:
            done.append(shard.close())
        if done:
            kinds = [pa.int32()] * 2 + [pa.string()] * 2 + [pa.int64()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*done, strict=True), kinds, strict=True)], names=names)

    rows.mapInArrow(encode, MANIFEST).write.parquet(f"{uri}/manifest")
    return manifest(spark, uri)


def manifest(spark: SparkSession, uri: str) -> DataFrame:
    """One row a shard, with the ids of all shards before it. The window's input is one row a shard."""
    m = spark.read.schema(MANIFEST).parquet(f"{uri}/manifest")
    before = Window.orderBy("part", "seq").rowsBetween(Window.unboundedPreceding, -1)
    return m.withColumn("base", F.coalesce(F.sum("n_ids").over(before), F.lit(0)).cast("long"))


def read_rows(spark: SparkSession, uri: str, read_bytes: int = 8 << 20) -> DataFrame:
    """Every stored document, read from the files: key, start, n_tokens, ids_crc32.

    The rows of each key are found through the shard's hash index (a key that it doesn't lead to is
    an error); rows without a key come from the row table. Ids are read ``read_bytes`` at a time.
    """
    shards = manifest(spark, uri)
    n = shards.count()
    shards = shards.select("ids_uri", "idx_uri", "base").repartition(max(1, min(n, 4 * spark.sparkContext.defaultParallelism)))

    def read(batches):
        for b in lean(batches):
            for s in b.to_pylist():
                idx = ShardIndex.parse(read_all(s["idx_uri"]))
                rows = np.concatenate([np.flatnonzero(~idx.has_key), idx.rows_of(np.unique(idx.keys[idx.has_key]))])
                starts, lengths = idx.starts[rows], idx.lengths[rows]
                crc = [zlib.crc32(ids.astype("<u4").data) for ids in stored(s["ids_uri"], starts, lengths, read_bytes)]
                yield pa.RecordBatch.from_arrays([pa.array(idx.keys[rows], mask=~idx.has_key[rows]), pa.array(starts + s["base"]), pa.array(lengths), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return shards.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def stored(uri: str, starts: np.ndarray, lengths: np.ndarray, read_bytes: int):
    """The ids of rows of a shard; rows that stand end to end are read together."""
    width, at = id_width(read_range(uri, 0, HEADER_SIZE)), 0
    ends = starts + lengths
    apart = np.append(np.flatnonzero(starts[1:] != ends[:-1]) + 1, len(starts))
    while at < len(starts):
        last = int(np.searchsorted(ends[at : apart[np.searchsorted(apart, at, "right")]], starts[at] + read_bytes // width, "right")) + at
        last = max(at + 1, last)
        raw = np.frombuffer(read_range(uri, HEADER_SIZE + int(starts[at]) * width, int(ends[last - 1] - starts[at]) * width), f"<u{width}")
        for a, n in zip((starts[at:last] - starts[at]).tolist(), lengths[at:last].tolist(), strict=True):
            yield raw[a : a + n]
        at = last


def lookup(spark: SparkSession, uri: str, keys: list[int]) -> dict[int, list[np.ndarray]]:
    """Ids of the rows of some keys, in one job. A key costs a fixed number of small reads in each shard
    whose key range holds it: bits and ranks of its levels, its slot, its row, its ids."""
    asked = spark.createDataFrame([(k,) for k in dict.fromkeys(keys)], "k long")
    m = spark.read.schema(MANIFEST).parquet(f"{uri}/manifest").select("part", "seq", "min_key", "max_key", "ids_uri", "idx_uri")
    where = m.join(F.broadcast(asked), F.col("k").between(F.col("min_key"), F.col("max_key"))).drop("min_key", "max_key")

    def find(batches):
        for b in lean(batches):
            shards: dict = {}
            for r in b.to_pylist():
                idx = shards.get(r["idx_uri"]) or shards.setdefault(r["idx_uri"], ShardIndex.open(r["idx_uri"]))
                row, width, out = int(idx.find(np.array([r["k"]], np.int64))[0]), id_width(read_range(r["ids_uri"], 0, HEADER_SIZE)), []
                while 0 <= row < len(idx.keys) and idx.has_key[row] and idx.keys[row] == r["k"]:
                    raw = read_range(r["ids_uri"], HEADER_SIZE + int(idx.starts[row]) * width, int(idx.lengths[row]) * width)
                    out.append((r["k"], r["part"], r["seq"], row, raw, width))
                    row += 1
                if out:
                    kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.int32())
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["k", "part", "seq", "row", "ids", "width"])

    found: dict[int, list[np.ndarray]] = {k: [] for k in keys}
    for r in where.mapInArrow(find, "k long, part int, seq int, row long, ids binary, width int").orderBy("k", "part", "seq", "row").toLocalIterator():
        found[r["k"]].append(np.frombuffer(r["ids"], f"<u{r['width']}"))
    return found


def store_tokens(docs: DataFrame, **options) -> DataFrame:
    """Write to a new place in the shared folder and read back."""
    uri = workspace.fresh(docs.sparkSession, "tokens")
    write_tokens(docs, uri, **options)
    return read_rows(docs.sparkSession, uri)
