"""Seeded total orders that do not depend on ids, equal in every engine: the first 48 bits of an md5."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 48


def prio(seed: int | str, *columns: str | Column) -> Column:
    """A BIGINT in [0, 2^48) for each row; ties are left to the ids."""
    text = F.concat_ws("-", *(F.col(c).cast("string") if isinstance(c, str) else c.cast("string") for c in columns))
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), text)), 1, 12), 16, 10).cast("bigint")


def prio_sql(seed: int | str, text: str) -> str:
    return f"('0x' || substr(md5('{seed}:' || {text}), 1, 12))::BIGINT"


def shift(seed: int, beta: float, column: str) -> Column:
    """An exponential shift in millionths, quantised once: all later comparisons are between integers."""
    return F.floor(-F.log((prio(seed, column) + 1) / F.lit(float(SPAN))) / beta * 1e6).cast("bigint")
