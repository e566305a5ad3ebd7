"""Keyed randomness: a retry, another partitioning or another engine draws the same numbers."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

_SPAN = 16**13


def uniform(*keys: Column | str, kind: str = "md5") -> Column:
    """A number in (0, 1) from the keys joined by '|': 52 bits of md5, or of xxhash64 where speed matters more."""
    text = F.concat_ws("|", *[k if isinstance(k, Column) else F.lit(k) for k in keys])
    if kind == "md5":
        bits = F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long")
    else:
        bits = F.shiftrightunsigned(F.xxhash64(text), 12)
    return (bits.cast("double") + 0.5) / F.lit(float(_SPAN))


def gumbel(u: Column) -> Column:
    """A Gumbel variate of a uniform one."""
    return -F.log(-F.log(u))


def draw(*keys: object) -> float:
    """The same uniform number in Python."""
    return (int(hashlib.md5("|".join(map(str, keys)).encode()).hexdigest()[:13], 16) + 0.5) / _SPAN


def uniform_sql(*keys: str) -> str:
    """The same uniform number in DuckDB."""
    return f"((('0x' || substr(md5(concat_ws('|', {', '.join(keys)})), 1, 13))::BIGINT)::DOUBLE + 0.5) / {float(_SPAN)}"
