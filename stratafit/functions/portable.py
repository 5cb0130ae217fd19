"""Random numbers that any SQL engine can make again: digits of an md5 of seed and counters."""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column
from pyspark.sql import functions as F

_SPAN = 2**52


def _key(parts: tuple[Column | str | int, ...]) -> Column:
    return F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])


def bits(*parts: Column | str | int) -> Column:
    """52 random bits as a long."""
    return F.conv(F.substring(F.md5(_key(parts)), 1, 13), 16, 10).cast("long")


def uniform(*parts: Column | str | int) -> Column:
    """In [0, 1)."""
    return bits(*parts) / F.lit(float(_SPAN))


def normal(*parts: Column | str | int) -> Column:
    """Standard normal, from two uniforms."""
    return F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - uniform(*parts, "a"))) * F.cos(F.lit(2 * math.pi) * uniform(*parts, "b"))


def sql_uniform(*parts: str) -> str:
    """The same number in DuckDB; parts are SQL expressions."""
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 13))::BIGINT / {float(_SPAN)})"


def sql_normal(*parts: str) -> str:
    return f"(sqrt(-2.0 * ln(1.0 - {sql_uniform(*parts, repr('a'))})) * cos({2 * math.pi!r} * {sql_uniform(*parts, repr('b'))}))"


def py_uniform(*parts: object) -> float:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) / _SPAN
