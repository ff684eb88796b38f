"""Expressions that the workloads share with their SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def luck(*parts: Column | str) -> Column:
    """A number in [0, 10000) by hash; the same in both engines."""
    text = F.concat_ws("|", *[F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts])
    return (F.conv(F.substring(F.md5(text), 1, 7), 16, 10).cast("long") % 10_000).cast("int")


def luck_sql(*parts: str) -> str:
    """SQL of luck; parts are SQL expressions of text."""
    return f"(CAST('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 7) AS BIGINT) % 10000)"


def r6(c: Column) -> Column:
    return F.round(c.cast("double"), 6)
