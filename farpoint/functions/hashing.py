"""Deterministic draws: a retried or repeated task draws the same numbers."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

DIGITS = 13
SPAN = 1 << (4 * DIGITS)


def md5_number(*parts: Column | str | int) -> Column:
    """The first 13 hex digits of md5 of the parts joined by colons, as a BIGINT."""
    text = F.concat_ws(":", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, DIGITS), 16, 10).cast("bigint")


def md5_uniform(*parts: Column | str | int) -> Column:
    """Uniform in [0, 1), the same in Spark and DuckDB."""
    return md5_number(*parts) / F.lit(float(SPAN))


def md5_below(rate: float, *parts: Column | str | int) -> Column:
    """md5_uniform(...) < rate, told by the hex digits alone, which is cheaper."""
    most = math.ceil(rate * SPAN)  # exact: a double times a power of two
    if most >= SPAN:
        return F.lit(True)
    text = F.concat_ws(":", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.md5(text.cast("binary")) < F.lit(f"{most:0{DIGITS}x}")


def fast_uniform(*parts: Column | str | int) -> Column:
    """Uniform in [0, 1) from xxhash64; cheaper, for data of which no other engine needs the draws."""
    return F.shiftrightunsigned(F.xxhash64(*[p if isinstance(p, Column) else F.lit(p) for p in parts]), 11) / F.lit(float(1 << 53))


def duck_number(*parts: str) -> str:
    """DuckDB text of md5_number; the parts are SQL expressions of type text."""
    text = " || ':' || ".join(parts)
    return f"CAST(('0x' || substr(md5({text}), 1, {DIGITS})) AS BIGINT)"


def duck_uniform(*parts: str) -> str:
    """DuckDB text of md5_uniform."""
    return f"({duck_number(*parts)} / {float(SPAN)!r})"
