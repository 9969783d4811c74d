"""Files of the token-id store, on any file system that pyarrow reaches."""

from __future__ import annotations

import io
import json
import os
import struct
import uuid

import numpy as np

from fsmeta.llm.common import mix

#: Fixed values of the file format.
MAGIC = b"TIDSHRD1"
HEADER = "<8sIIQ"  # magic, bytes an id, two reserved fields
HEADER_SIZE = struct.calcsize(HEADER)
GAMMA, LEVELS = 2.0, 48


def header(width: int) -> bytes:
    return struct.pack(HEADER, MAGIC, width, 0, 0)


def id_width(head: bytes) -> int:
    magic, width, _, _ = struct.unpack_from(HEADER, head)
    if magic != MAGIC:
        raise ValueError("not an id shard")
    return width


def _fs(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else "file://" + os.path.abspath(uri.removeprefix("file:")))


class Replaced:
    """A file that appears under its name only when complete, so a retried task replaces it."""

    def __init__(self, uri: str):
        self.fs, self.path = _fs(uri)
        self.part = f"{self.path}.{uuid.uuid4().hex[:8]}.part"
        self.fs.create_dir(os.path.dirname(self.path), recursive=True)
        self.out = self.fs.open_output_stream(self.part)

    def write(self, data: bytes) -> None:
        self.out.write(data)

    def close(self) -> None:
        self.out.close()
        self.fs.move(self.part, self.path)

    def drop(self) -> None:
        self.out.close()
        self.fs.delete_file(self.part)


def read_all(uri: str) -> bytes:
    fs, path = _fs(uri)
    with fs.open_input_stream(path) as f:
        return f.read()


def read_range(uri: str, start: int, n: int) -> bytes:
    fs, path = _fs(uri)
    with fs.open_input_file(path) as f:
        return f.read_at(n, start)


class Ranged:
    """An array inside a file, of which only the elements asked for are read."""

    def __init__(self, file, start: int, kind: str, length: int):
        self.file, self.start, self.dtype, self.length = file, start, np.dtype(kind), length

    def __len__(self) -> int:
        return self.length

    def __getitem__(self, at):
        size = self.dtype.itemsize
        if np.ndim(at) == 0:
            return np.frombuffer(self.file.read_at(size, self.start + int(at) * size), self.dtype)[0]
        return np.array([self[i] for i in np.asarray(at).tolist()], self.dtype)


class PerfectHash:
    """Minimal perfect hash over distinct 64-bit keys.

    Each level has a bit array of twice the keys that are left; a key that is alone on its
    bit is settled there, the others go on to the next level. The slot of a key is the rank
    of its bit. All steps are array operations; a look-up takes 1.5 levels on average.
    """

    def __init__(self, sizes: np.ndarray, bits: np.ndarray, ranks: np.ndarray):
        self.sizes, self.bits, self.ranks = sizes, bits, ranks
        self.starts = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64)

    @staticmethod
    def place(keys: np.ndarray, level: int, size: int) -> np.ndarray:
        return (mix(keys ^ mix(np.full(1, level + 1, np.uint64))) % np.uint64(size)).astype(np.int64)

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        left, sizes, all_bits = keys.astype(np.uint64), [], []
        for level in range(LEVELS):
            if not len(left):
                break
            size = max(8, int(GAMMA * len(left)) + 7 & ~7)
            at = cls.place(left, level, size)
            alone = np.bincount(at, minlength=size) == 1
            sizes.append(size)
            all_bits.append(alone)
            left = left[~alone[at]]
        if len(left):
            raise ValueError("keys are not distinct")
        flat = np.concatenate(all_bits) if all_bits else np.zeros(0, bool)
        bits = np.packbits(flat, bitorder="little")
        ranks = np.concatenate([[0], np.cumsum(flat.reshape(-1, 8).sum(1))[:-1]]).astype(np.uint32) if len(flat) else np.zeros(0, np.uint32)
        return cls(np.array(sizes, np.int64), bits, ranks)

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """Slot of each key; -1 where no level has a bit for it. Unknown keys may get a slot: the fingerprint tells."""
        keys, out, left = keys.astype(np.uint64), np.full(len(keys), -1, np.int64), np.arange(len(keys))
        for level, size in enumerate(self.sizes.tolist()):
            if not len(left):
                break
            at = self.place(keys[left], level, size) + self.starts[level]
            byte, bit = at >> 3, (at & 7).astype(np.uint8)
            got = (self.bits[byte] >> bit) & 1 == 1
            below = np.unpackbits((self.bits[byte] & ((np.uint16(1) << bit) - 1).astype(np.uint8))[:, None], axis=1).sum(1)
            out[left[got]] = (self.ranks[byte] + below)[got]
            left = left[~got]
        return out


def key_hash(keys: np.ndarray) -> np.ndarray:
    return mix(keys.astype(np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15))


def fingerprint(keys: np.ndarray) -> np.ndarray:
    return (mix(keys.astype(np.int64).view(np.uint64) ^ np.uint64(0xD1B54A32D192ED03)) >> np.uint64(32)).astype(np.uint32)


class ShardIndex:
    """Rows of a shard (key, where its ids begin, how many) and the hash from key to first row.

    Rows of equal keys stand side by side; rows without a key are kept but not indexed.
    """

    FIELDS = ("keys", "has_key", "starts", "lengths", "sizes", "bits", "ranks", "first", "prints")

    def __init__(self, **arrays: np.ndarray):
        self.__dict__.update(arrays)
        self.hash = PerfectHash(self.sizes, self.bits, self.ranks)

    @classmethod
    def build(cls, keys: np.ndarray, has_key: np.ndarray, lengths: np.ndarray) -> ShardIndex:
        starts = np.concatenate([[0], np.cumsum(lengths)[:-1]]).astype(np.int64) if len(lengths) else np.zeros(0, np.int64)
        rows = np.flatnonzero(has_key)
        distinct, at = np.unique(keys[rows], return_index=True)
        perfect = PerfectHash.build(key_hash(distinct))
        slot = perfect.slots(key_hash(distinct))
        first, prints = np.zeros(len(distinct), np.int64), np.zeros(len(distinct), np.uint32)
        first[slot], prints[slot] = rows[at], fingerprint(distinct)
        return cls(keys=keys, has_key=has_key, starts=starts, lengths=lengths, sizes=perfect.sizes, bits=perfect.bits, ranks=perfect.ranks, first=first, prints=prints)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """First row of each key, -1 where the shard has no such key."""
        slot = self.hash.slots(key_hash(keys))
        ok = slot >= 0
        ok[ok] = self.prints[slot[ok]] == fingerprint(keys[ok])
        row = np.full(len(keys), -1, np.int64)
        row[ok] = self.first[slot[ok]]
        ok[ok] = self.keys[row[ok]] == keys[ok]
        row[~ok] = -1
        return row

    def rows_of(self, keys: np.ndarray) -> np.ndarray:
        """All rows of distinct keys that the shard has, each found through its slot, key after key."""
        first = self.find(keys)
        if (first < 0).any():
            raise ValueError("the index misses keys")
        # rows of equal keys stand side by side
        new = np.ones(len(self.keys), bool)
        new[1:] = (self.keys[1:] != self.keys[:-1]) | (self.has_key[1:] != self.has_key[:-1])
        start = np.append(np.flatnonzero(new), len(self.keys))
        many = start[np.searchsorted(start, first, "right")] - first
        return np.repeat(first - np.cumsum(many) + many, many) + np.arange(int(many.sum()))

    def dump(self) -> bytes:
        out, parts, head = io.BytesIO(), [], {}
        for name in self.FIELDS:
            a = np.ascontiguousarray(getattr(self, name))
            head[name] = (a.dtype.str, len(a))
            parts.append(a.tobytes())
        meta = json.dumps(head).encode()
        out.write(struct.pack("<I", len(meta)) + meta + b"".join(parts))
        return out.getvalue()

    @classmethod
    def open(cls, uri: str) -> ShardIndex:
        """For a few look-ups: the head and the level sizes are read, and of all else single elements."""
        fs, path = _fs(uri)
        file = fs.open_input_file(path)
        n = struct.unpack("<I", file.read_at(4, 0))[0]
        at, arrays = 4 + n, {}
        for name, (kind, length) in json.loads(file.read_at(n, 4)).items():
            arrays[name] = Ranged(file, at, kind, length)
            at += arrays[name].dtype.itemsize * length
        arrays["sizes"] = arrays["sizes"][np.arange(len(arrays["sizes"]))]
        return cls(**arrays)

    @classmethod
    def parse(cls, data: bytes) -> ShardIndex:
        n = struct.unpack_from("<I", data)[0]
        at, arrays = 4 + n, {}
        for name, (kind, length) in json.loads(data[4 : 4 + n]).items():
            arrays[name] = np.frombuffer(data, kind, length, at)
            at += arrays[name].nbytes
        return cls(**arrays)
