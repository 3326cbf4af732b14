"""Random numbers that depend on names only: equal in Spark, DuckDB and Python, whatever the partitioning."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def portable_uniform(*parts: Column | str | int) -> Column:
    """In [0, 1): the first eight hex digits of an md5 over the parts, joined by colons. Strings are literals."""
    joined = F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(joined), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def uniform_sql(*parts: str) -> str:
    """The same in DuckDB's SQL; parts are SQL expressions of type text."""
    return f"(('0x' || substr(md5(concat_ws(':', {', '.join(parts)})), 1, 8))::BIGINT / 4294967296.0)"


def uniform_for(*parts: object) -> float:
    """The same for Python values."""
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:8], 16) / 4294967296.0
