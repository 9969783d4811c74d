"""Event ingestion: both feeds to uniform events, and the filter for events that say little."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

UNIFORM = ("source_id", "seq", "ts", "op", "fid", "is_dir", "parent_fid", "name", "size")
#: Operation codes of the text feed and their uniform names.
TEXT_OPS = {"01CREAT": "CREATE", "02MKDIR": "MKDIR", "06UNLNK": "UNLINK", "07RMDIR": "RMDIR", "08RENME": "RENAME", "10OPEN": "OPEN", "11CLOSE": "CLOSE", "14SATTR": "SETATTR"}
WATCH = "source long, seq long, ts string, event string, inode long, dir boolean, parent long, name string, size long"
WATCH_OPS = {"IN_CREATE": "CREATE", "IN_MKDIR": "MKDIR", "IN_DELETE": "UNLINK", "IN_RMDIR": "RMDIR", "IN_MOVED_TO": "RENAME", "IN_OPEN": "OPEN", "IN_CLOSE_WRITE": "CLOSE", "IN_ATTRIB": "SETATTR"}


def _op(column, ops: dict):
    flat = [F.lit(x) for kv in ops.items() for x in kv]
    return F.element_at(F.create_map(*flat), column)


def render_changelog(events: DataFrame) -> DataFrame:
    """Lines as the text feed has them: seq, code, time, t=[fid], d=[is_dir], p=[parent] and the name last. A rename
    names the moved object as its source, s=[fid], and where known the parent it comes from, sp=[parent]."""
    code = _op(F.col("op"), {v: k for k, v in TEXT_OPS.items()})
    part = lambda tag, c: F.when(F.col(c).isNotNull(), F.concat(F.lit(f" {tag}=["), F.col(c).cast("string"), F.lit("]"))).otherwise("")
    line = F.concat(F.col("seq").cast("string"), F.lit(" "), code, F.lit(" "), F.date_format(F.col("ts").cast("timestamp"), "yyyy-MM-dd'T'HH:mm:ss.SSSSSS"), F.when(F.col("op") == "RENAME", part("s", "fid")).otherwise(part("t", "fid")), part("sp", "source_parent_fid") if "source_parent_fid" in events.columns else F.lit(""), part("d", "is_dir"), part("p", "parent_fid"), F.when(F.col("name").isNotNull(), F.concat(F.lit(" "), "name")).otherwise(""))
    return events.select("source_id", line.alias("line"))


def parse_changelog(lines: DataFrame) -> DataFrame:
    """The text feed: no path and no stat in it, and none is looked up here. What a line has depends on its
    operation: renames give the moved object and its former parent as sources, others a target."""
    x = F.col("line")
    number = lambda tag: F.nullif(F.regexp_extract(x, rf" {tag}=\[(-?\d+)\]", 1), F.lit("")).cast("long")
    return lines.select(
        "source_id",
        F.split(x, " ")[0].cast("long").alias("seq"),
        F.to_timestamp_ntz(F.split(x, " ")[2], F.lit("yyyy-MM-dd'T'HH:mm:ss.SSSSSS")).alias("ts"),
        _op(F.split(x, " ")[1], TEXT_OPS).alias("op"),
        F.coalesce(number("s"), number("t")).alias("fid"),
        (F.regexp_extract(x, r" d=\[(\w+)\]", 1) == "true").alias("is_dir"),
        number("p").alias("parent_fid"),
        F.nullif(F.regexp_extract(x, r" p=\[-?\d+\] (.*)$", 1), F.lit("")).alias("name"),
        F.lit(None).cast("long").alias("size"),
        number("sp").alias("source_parent_fid"),
    )


def render_watch(events: DataFrame) -> DataFrame:
    """JSON messages as the watch feed has them, with the stat inside."""
    event = _op(F.col("op"), {v: k for k, v in WATCH_OPS.items()})
    body = F.struct(F.col("source_id").alias("source"), "seq", F.date_format(F.col("ts").cast("timestamp"), "yyyy-MM-dd'T'HH:mm:ss.SSSSSS").alias("ts"), event.alias("event"), F.col("fid").alias("inode"), F.col("is_dir").alias("dir"), F.col("parent_fid").alias("parent"), "name", "size")
    return events.select(F.to_json(body).alias("message"))


def parse_watch(messages: DataFrame) -> DataFrame:
    m = messages.select(F.from_json("message", WATCH).alias("m"))
    return m.select(F.col("m.source").alias("source_id"), "m.seq", F.to_timestamp_ntz(F.col("m.ts"), F.lit("yyyy-MM-dd'T'HH:mm:ss.SSSSSS")).alias("ts"), _op(F.col("m.event"), WATCH_OPS).alias("op"), F.col("m.inode").alias("fid"), F.col("m.dir").alias("is_dir"), F.col("m.parent").alias("parent_fid"), "m.name", "m.size")


ADAPTERS = {"changelog": parse_changelog, "watch": parse_watch, "uniform": lambda df: df.select(*UNIFORM)}


def to_uniform(feed: DataFrame, adapter: str) -> DataFrame:
    return ADAPTERS[adapter](feed).select(*UNIFORM)


def union_feeds(*feeds: DataFrame) -> DataFrame:
    out = feeds[0]
    for f in feeds[1:]:
        out = out.unionByName(f, allowMissingColumns=True)
    return out


def filter_low_information(events: DataFrame, drop: tuple[str, ...] = ("OPEN",)) -> DataFrame:
    """Before any shuffle."""
    return events.filter(~F.col("op").isin(*drop)) if drop else events
