"""Primary records: one JSON document for each object, packed into bounded ingest requests."""

from __future__ import annotations

import time
import zlib
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fsmeta.functions.paths import mode_text

TIMES = ("atime", "ctime", "mtime")


def visible_to(admins: tuple[str, ...] = ("group:admins",)):
    return F.array(F.concat(F.lit("user:"), "uid"), F.concat(F.lit("group:"), "gid"), *map(F.lit, admins))


def to_records(df: DataFrame, admins: tuple[str, ...] = ("group:admins",), extra: tuple[str, ...] = ("fileset", "checksum", "project")) -> DataFrame:
    """subject, visible_to, content: narrow, no shuffle."""
    iso = [F.date_format(F.col(t).cast("timestamp"), "yyyy-MM-dd'T'HH:mm:ssXXX").alias(t) for t in TIMES]
    raw = F.struct(F.col("mode").alias("mode"), *[F.unix_timestamp(F.col(t).cast("timestamp")).alias(t) for t in TIMES]).alias("raw")
    more = [F.col(c) for c in extra if c in df.columns]
    content = F.struct("type", mode_text(F.col("type"), F.col("mode")).alias("mode"), "uid", "gid", "size", *iso, *more, raw)
    return df.select(F.col("path").alias("subject"), visible_to(admins).alias("visible_to"), content.alias("content"))


def to_requests(records: DataFrame, max_bytes: int = 10 << 20, max_wait_s: float = 5.0, version: int = 0) -> DataFrame:
    """Requests of at most ``max_bytes`` (a lone larger record makes its own), packed within each task.

    A request also closes when the task has waited ``max_wait_s`` for further rows. Its id depends
    on version, partition and ordinal only, so a retry sends the same request.
    """
    lines = records.select("subject", F.to_json(F.struct("subject", "visible_to", "content")).alias("line"))

    def pack(batches):
        from pyspark import TaskContext

        part, ordinal, held, size, first, since = TaskContext.get().partitionId(), 0, [], 0, None, time.monotonic()

        def close():
            return pa.RecordBatch.from_arrays([pa.array([f"v{version}-{part:06d}-{ordinal:06d}"]), pa.array([len(held)]), pa.array([size]), pa.array([first]), pa.array(["\n".join(held)])], names=["request_id", "n_records", "n_bytes", "first_path", "payload"])

        for b in batches:
            if held and time.monotonic() - since >= max_wait_s:
                yield close()
                held, size, ordinal = [], 0, ordinal + 1
            since = time.monotonic()
            for subject, line in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                n = len(line.encode()) + bool(held)
                if held and size + n > max_bytes:
                    yield close()
                    held, size, ordinal, n = [], 0, ordinal + 1, n - 1
                first = subject if not held else first
                held.append(line)
                size += n
            since = time.monotonic()
        if held:
            yield close()

    return lines.mapInArrow(pack, "request_id string, n_records long, n_bytes long, first_path string, payload string")


def receipt(payload: str) -> str:
    """Stands in for an ingest service: the id that it would answer with."""
    return f"task-{zlib.crc32(payload.encode()):08x}"


def submit(requests: DataFrame, send: Callable[[str], str] = receipt, attempts: int = 3) -> DataFrame:
    """Send every request; one log row each: request_id, task_id (the service's asynchronous id, null if it was
    refused ``attempts`` times), n_records, n_bytes, tries. ``send`` runs in the tasks."""

    def work(batches):
        for b in batches:
            out = []
            for r in b.to_pylist():
                task, tries = None, 0
                while task is None and tries < attempts:
                    tries += 1
                    try:
                        task = send(r["payload"])
                    except OSError:
                        time.sleep(0.1 * tries)
                out.append((r["request_id"], task, r["n_records"], r["n_bytes"], tries))
            if out:
                kinds = (pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["request_id", "task_id", "n_records", "n_bytes", "tries"])

    return requests.mapInArrow(work, "request_id string, task_id string, n_records long, n_bytes long, tries int")


def audit(log: DataFrame, path: str, version: int) -> DataFrame:
    """Keep a version's submission log (written once: sending is not done again when it is read); gives it."""
    at = f"{path}/version={version}"
    log.write.mode("overwrite").parquet(at)
    return log.sparkSession.read.schema(log.schema).parquet(at)


def request_log(requests: DataFrame, kind: str = "ingest") -> DataFrame:
    return requests.select("request_id", F.lit(kind).alias("kind"), "n_records", "n_bytes", "first_path")


def index_stats(df: DataFrame) -> DataFrame:
    """Records, bytes, users, groups and links of a reduced snapshot."""
    return df.agg(F.count("*").alias("records"), F.sum("size").alias("bytes"), F.countDistinct("uid").alias("users"), F.countDistinct("gid").alias("groups"), F.count_if(F.col("type") == "l").alias("links"))
