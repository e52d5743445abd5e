"""Hashes that decide every random choice: of keys only, so a retried task draws the same.

``h32`` (md5) gives the same number in other engines and serves where results are compared with SQL;
``fast`` (xxhash64) is for production runs.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

TWO32 = 4294967296


def h32(*parts) -> Column:
    """First 32 bits of md5 of the parts joined by colons, as a long."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[c.cast("string") for c in cols])), 1, 8), 16, 10).cast("long")


def unit(*parts) -> Column:
    """h32 scaled to [0, 1)."""
    return h32(*parts) / F.lit(float(TWO32))


def fast(*parts) -> Column:
    """Nonnegative 63-bit hash of the parts."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.xxhash64(*cols).bitwiseAND(F.lit((1 << 63) - 1))


def py_h32(*parts) -> int:
    """h32 on the driver or in a task."""
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:8], 16)


def sql_h32(*parts: str) -> str:
    """h32 as SQL for the checking engine; parts are SQL expressions."""
    joined = " || ':' || ".join(f"({p})::VARCHAR" for p in parts)
    return f"('0x' || substr(md5({joined}), 1, 8))::BIGINT"
