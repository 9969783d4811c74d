"""Event feeds as streams: text lines with acknowledged offsets, JSON files, Kafka where its connector is."""

from __future__ import annotations

import json
import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceStreamReader, InputPartition


class Lines(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


class ChangelogReader(DataSourceStreamReader):
    """A folder with one append-only text file per source, ``<source_id>.log``. Offsets are bytes per file;
    ``commit`` notes what has been consumed, as the feed's own clearing does, and a new query begins there.
    Offsets stand after whole lines only: what is still being written is left for the next micro-batch."""

    def __init__(self, options: dict):
        self.root = options["path"].removeprefix("file://")

    def initialOffset(self) -> dict:  # noqa: N802
        try:
            with open(os.path.join(self.root, "cleared.json")) as f:
                return json.load(f)
        except FileNotFoundError:
            return {}

    def latestOffset(self) -> dict:  # noqa: N802
        return {n: self._whole(os.path.join(self.root, n)) for n in sorted(os.listdir(self.root)) if n.endswith(".log")}

    @staticmethod
    def _whole(path: str, step: int = 1 << 16) -> int:
        """The place after the last line end of a file."""
        with open(path, "rb") as f:
            at = f.seek(0, os.SEEK_END)
            while at > 0:
                start = max(0, at - step)
                f.seek(start)
                found = f.read(at - start).rfind(b"\n")
                if found >= 0:
                    return start + found + 1
                at = start
        return 0

    def partitions(self, start: dict, end: dict) -> list[Lines]:
        return [Lines(os.path.join(self.root, n), int(start.get(n, 0)), int(e)) for n, e in end.items() if int(e) > int(start.get(n, 0))]

    def read(self, partition: Lines):
        source = int(os.path.basename(partition.path).removesuffix(".log"))
        with open(partition.path, "rb") as f:
            f.seek(partition.start)
            left = partition.end - partition.start
            for raw in f:  # lines end at a line feed only: names may hold other separators
                left -= len(raw)
                if left < 0:
                    break
                if line := raw.removesuffix(b"\n").removesuffix(b"\r").decode(errors="replace"):
                    yield (source, line)

    def commit(self, end: dict) -> None:
        part = os.path.join(self.root, "cleared.json.part")
        with open(part, "w") as f:
            json.dump(end, f)
        os.replace(part, os.path.join(self.root, "cleared.json"))


class ChangelogSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "fschangelog"

    def schema(self) -> str:
        return "source_id long, line string"

    def streamReader(self, schema) -> ChangelogReader:  # noqa: N802
        return ChangelogReader(self.options)


def read_changelog(spark: SparkSession, path: str) -> DataFrame:
    spark.dataSource.register(ChangelogSource)
    return spark.readStream.format("fschangelog").option("path", path).load()


def read_watch(spark: SparkSession, path: str) -> DataFrame:
    """JSON messages, one a line."""
    return spark.readStream.text(path).withColumnRenamed("value", "message")


def read_kafka(spark: SparkSession, servers: str, topic: str) -> DataFrame:
    """Watch feed from its queue; needs the public Kafka connector on the class path."""
    return spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", topic).load().selectExpr("CAST(value AS STRING) AS message")
