"""Repeatable randomness: integers from md5 of a text, the same in Spark, SQL and Python.

The text is the parts joined by '|'; the number is its first 8 hexadecimal digits. xxhash64 would be cheaper but has
no counterpart in other SQL engines, so it is kept for places that nothing is compared with.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def h32(*parts) -> Column:
    """0 .. 2**32 - 1 from the parts, columns or plain values."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in cols])), 1, 8), 16, 10).cast("long")


def h32_sql(*parts: str) -> str:
    """h32 for DuckDB; the parts are SQL expressions."""
    return "CAST('0x' || substr(md5(" + " || '|' || ".join(f"CAST({p} AS VARCHAR)" for p in parts) + "), 1, 8) AS BIGINT)"


def h32_of(*parts) -> int:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16)
