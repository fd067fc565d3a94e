"""Seeded draws that Spark, DuckDB and Python compute alike: the first 13 hexadecimal digits of an MD5, as 52 bits."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def draw(*parts: Column) -> Column:
    """52-bit draw of the parts joined by colons."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts])), 1, 13), 16, 10).cast("bigint")


def draw_sql(*parts: str) -> str:
    return f"CAST('0x' || substr(md5(concat_ws(':', {', '.join(f'CAST({p} AS VARCHAR)' for p in parts)})), 1, 13) AS BIGINT)"


def draw_py(*parts) -> int:
    return int(hashlib.md5(":".join(str(p) for p in parts).encode()).hexdigest()[:13], 16)


def unit(draw_: Column) -> Column:
    """In (0, 1)."""
    return (draw_.cast("double") + 0.5) / 4503599627370496.0


def unit_sql(draw_: str) -> str:
    return f"((CAST({draw_} AS DOUBLE) + 0.5) / 4503599627370496.0)"


def share_of(draw_: Column, total: Column) -> Column:
    """A draw scaled to 0 .. total - 1: equally likely to 2**-52 of the total, however large it is."""
    return F.call_function("div", draw_.cast("decimal(16,0)") * total.cast("decimal(21,0)"), F.lit(1 << 52).cast("decimal(16,0)"))


def share_sql(draw_: str, total: str) -> str:
    return f"CAST(CAST({draw_} AS HUGEINT) * {total} // 4503599627370496 AS BIGINT)"


def trailing_zeros(v: Column) -> Column:
    """Number of low bits that are 0; v is a bigint with 52 bits at most, of 0 it is 52."""
    low = v.bitwiseAND(-v)
    return F.when(v == 0, F.lit(52)).otherwise(F.bit_count(low - 1)).cast("int")


def trailing_zeros_sql(v: str) -> str:
    return f"CAST(CASE WHEN {v} = 0 THEN 52 ELSE bit_count(({v} & -{v}) - 1) END AS INTEGER)"


def two_to(n) -> Column:
    """2 to the power of an integer column, as a bigint."""
    return F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col(n) if isinstance(n, str) else n)
