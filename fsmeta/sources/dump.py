"""Dump source: a snapshot of very many small SQLite files, one a directory, read in parallel.

``spark.read.format("fsdump").load(root)`` after ``register(spark)``. Partitions pack files by bytes, so
that millions of tiny files make a bounded number of tasks; only the columns of the schema are
selected, and simple comparisons are pushed into the files' queries. Files are read through the
local path that every executor sees (a shared mount).
"""

from __future__ import annotations

import os
import sqlite3
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual

SCHEMA = "name string, type string, mode int, uid long, gid long, size long, atime long, ctime long, mtime long"
#: Comparisons as SQL has them.
OPS = {EqualTo: "=", GreaterThan: ">", GreaterThanOrEqual: ">=", LessThan: "<", LessThanOrEqual: "<="}


@dataclass
class Files(InputPartition):
    paths: tuple[str, ...]


class DumpReader(DataSourceReader):
    def __init__(self, schema, options: dict):
        self.columns, self.root = [f.name for f in schema.fields], options["path"].removeprefix("file://")
        self.table, self.suffix = options.get("table", "entries"), options.get("suffix", ".db")
        self.pack = int(options.get("packBytes", 32 << 20))
        self.where, self.values = [], []

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        for f in filters:
            column = getattr(f, "attribute", ())
            if len(column) == 1 and column[0] in self.columns and column[0] != "path":
                if type(f) in OPS:
                    self.where.append(f'"{column[0]}" {OPS[type(f)]} ?')
                    self.values.append(f.value)
                    continue
                if isinstance(f, In):
                    self.where.append(f'"{column[0]}" IN ({", ".join("?" * len(f.value))})')
                    self.values += list(f.value)
                    continue
            yield f

    def partitions(self) -> list[Files]:
        out, held, size = [], [], 0
        for folder, dirs, names in os.walk(self.root):
            dirs.sort()
            for n in sorted(names):
                if n.endswith(self.suffix):
                    p = os.path.join(folder, n)
                    held.append(p)
                    size += os.path.getsize(p)
                    if size >= self.pack:
                        out.append(Files(tuple(held)))
                        held, size = [], 0
        return out + ([Files(tuple(held))] if held or not out else [])

    def read(self, partition: Files) -> Iterator[tuple]:
        wanted = ", ".join("?" if c == "path" else f'"{c}"' for c in self.columns)
        where = f" WHERE {' AND '.join(self.where)}" if self.where else ""
        for p in partition.paths:
            with sqlite3.connect(f"file:{p}?mode=ro", uri=True) as con:
                folder = os.path.relpath(os.path.dirname(p), self.root)
                folder = "/" if folder == "." else "/" + folder
                bound = [folder] * self.columns.count("path") + self.values
                for row in con.execute(f"SELECT {wanted} FROM {self.table}{where}", bound):
                    yield tuple(row)
            con.close()


class DumpDataSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "fsdump"

    def schema(self) -> str:
        return "path string, " + SCHEMA

    def reader(self, schema) -> DumpReader:
        return DumpReader(schema, self.options)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(DumpDataSource)


def write_dump(rows: dict[str, list[tuple]], root: str) -> None:
    """Directory -> rows as (name, type, mode, uid, gid, size, atime, ctime, mtime); for tests and samples."""
    for folder, own in rows.items():
        at = os.path.join(root, folder.strip("/"))
        os.makedirs(at, exist_ok=True)
        con = sqlite3.connect(os.path.join(at, "db.db"))
        con.execute("CREATE TABLE entries (name TEXT, type TEXT, mode INT, uid INT, gid INT, size INT, atime INT, ctime INT, mtime INT, inode INT, nlink INT, blksize INT, blocks INT, xattrs TEXT)")
        con.executemany("INSERT INTO entries VALUES (?,?,?,?,?,?,?,?,?,0,1,4096,8,'')", own)
        con.commit()
        con.close()
