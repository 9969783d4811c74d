"""Column functions on paths and mode bits, and their SQL registration."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import Row

#: Characters that a comma-separated file can't hold as they are, and their escapes.
ESCAPES = (("\\", "\\b"), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t"), (",", "\\c"), ('"', "\\q"), ("#", "\\h"), ("?", "\\w"))


def escape_path(path: Column) -> Column:
    for char, code in ESCAPES:
        path = F.replace(path, F.lit(char), F.lit(code))
    return path


def unescape_path(path: Column) -> Column:
    """Inverse of escape_path: every backslash in an escaped path begins a code, its own comes last."""
    for char, code in reversed(ESCAPES):
        path = F.replace(path, F.lit(code), F.lit(char))
    return path


def parts(path: Column) -> Column:
    """Directory names of a path, without its last name."""
    return F.slice(F.split(path, "/"), 2, F.greatest(F.size(F.split(path, "/")) - 2, F.lit(0)))


def prefix(path: Column, depth: Column | int) -> Column:
    """The directory of a path cut to at most ``depth`` levels; '/' for none."""
    p = parts(path)
    return F.concat(F.lit("/"), F.array_join(F.slice(p, 1, F.least(F.lit(depth) if isinstance(depth, int) else depth, F.size(p))), "/"))


def prefixes(path: Column, low: int, high: int) -> Column:
    """All directory prefixes of a path from level ``low`` to ``high``."""
    p = parts(path)
    top = F.least(F.lit(high), F.size(p))
    levels = F.when(top >= low, F.sequence(F.lit(low), top)).otherwise(F.array().cast("array<int>"))
    return F.transform(levels, lambda n: F.concat(F.lit("/"), F.array_join(F.slice(p, 1, n), "/")))


def mode_text(kind: Column, mode: Column) -> Column:
    """Like -rw-r--r--, with set-id and sticky bits. ``mode``: octal digits written in decimal."""
    text = F.when(kind == "f", "-").when(kind == "l", "l").otherwise("d")
    special = F.floor(mode / 1000) % 10
    for place, bit, on, off in ((100, 4, "s", "S"), (10, 2, "s", "S"), (1, 1, "t", "T")):
        digit = F.floor(mode / place) % 10
        x = digit.bitwiseAND(F.lit(1)) > 0
        extra = special.bitwiseAND(F.lit(bit)) > 0
        last = F.when(extra & x, on).when(extra, off).when(x, "x").otherwise("-")
        text = F.concat(text, F.when(digit.bitwiseAND(F.lit(4)) > 0, "r").otherwise("-"), F.when(digit.bitwiseAND(F.lit(2)) > 0, "w").otherwise("-"), last)
    return text


def dd_bucket(value: Column, alpha: float) -> Column:
    import math

    return F.ceil(F.log(value) / math.log((1 + alpha) / (1 - alpha))).cast("long")


def register(spark: SparkSession) -> None:
    """SQL names: path_prefixes (table function), mode_text, escape_path, unescape_path, dd_bucket."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="depth int, prefix string")
    class PathPrefixes:
        def eval(self, path: Row, dmin: int, dmax: int):
            names = [x for x in (path or "").split("/")[:-1] if x]
            for n in range(dmin, min(dmax, len(names)) + 1):
                yield n, "/" + "/".join(names[:n])

    spark.udtf.register("path_prefixes", PathPrefixes)
    escapes = "path"
    for char, code in ESCAPES:
        escapes = f"replace({escapes}, {_literal(char)}, {_literal(code)})"
    back = "path"
    for char, code in reversed(ESCAPES):
        back = f"replace({back}, {_literal(code)}, {_literal(char)})"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION escape_path(path STRING) RETURNS STRING RETURN {escapes}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION unescape_path(path STRING) RETURNS STRING RETURN {back}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dd_bucket(v DOUBLE, alpha DOUBLE) RETURNS BIGINT RETURN ceil(ln(v) / ln((1 + alpha) / (1 - alpha)))")


def _literal(text: str) -> str:
    return "decode(unhex('" + text.encode().hex() + "'), 'UTF-8')"
