"""Deterministic draws from md5, the same in any engine that has it."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash32(*parts: Column | str | int) -> Column:
    """The first eight hexadecimal digits of the md5 of the parts, joined by colons, as a number."""
    text = F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def uniform(*parts: Column | str | int) -> Column:
    """In [-0.5, 0.5)."""
    return hash32(*parts) / F.lit(4294967296.0) - 0.5


def gaussian(*parts: Column | str | int) -> Column:
    """A normal draw by Box and Muller's transform of two hashes."""
    one, two = hash32(*parts, 1), hash32(*parts, 2)
    return F.sqrt(-2 * F.log((one + 1) / F.lit(4294967297.0))) * F.cos(two / F.lit(4294967296.0) * (2 * 3.141592653589793))


def sql_hash32(text: str) -> str:
    """The same in DuckDB for an SQL string expression."""
    return f"CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT)"


def sql_uniform(text: str) -> str:
    return f"({sql_hash32(text)} / 4294967296.0 - 0.5)"
