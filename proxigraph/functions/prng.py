"""Portable pseudo-random draws: the same number in Spark, SQL and numpy, on any cluster layout."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Draws lie in [0, RANGE).
RANGE = 1 << 32


def draw(seed: int, *parts: Column | str | int) -> Column:
    """32-bit draw that depends on seed and the parts only."""
    cols = [F.lit(str(seed))]
    for p in parts:
        cols.append((F.col(p) if isinstance(p, str) else F.lit(p) if isinstance(p, int) else p).cast("string"))
    return F.conv(F.substring(F.md5(F.concat_ws(":", *cols)), 1, 8), 16, 10).cast("long")


def draw_value(seed: int, *parts) -> int:
    return int(hashlib.md5(":".join(map(str, (seed, *parts))).encode()).hexdigest()[:8], 16)


def draw_sql(seed: int, *parts: str) -> str:
    """The draw as a DuckDB expression over the named parts."""
    return f"('0x' || substr(md5(concat_ws(':', '{seed}', {', '.join(parts)})), 1, 8))::bigint"
