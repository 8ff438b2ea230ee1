"""Portable random numbers: the same draw in Spark, Python and ANSI SQL for a tag and a key.

A draw in [0, 1) is the first 13 hexadecimal digits of md5("tag:key") over 16**13.
"""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column
from pyspark.sql import functions as F

_SPAN = 16.0**13
#: Stands in for a draw of exactly 0 where a logarithm is taken.
TINY = 2.0**-52


def uniform(tag: str, key: Column) -> Column:
    digest = F.md5(F.concat(F.lit(f"{tag}:"), key.cast("string")).cast("binary"))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / F.lit(_SPAN)


def uniform_value(tag: str, key: object) -> float:
    return int(hashlib.md5(f"{tag}:{key}".encode()).hexdigest()[:13], 16) / _SPAN


def uniform_sql(tag: str, key: str) -> str:
    """DuckDB text of the same draw; ``key`` is a SQL expression of an integer or string."""
    return f"(('0x' || substr(md5('{tag}:' || CAST({key} AS VARCHAR)), 1, 13))::UBIGINT::DOUBLE / 4503599627370496.0)"


def gaussian(tag: str, key: Column) -> Column:
    """Box-Muller from two draws."""
    radius = F.sqrt(F.lit(-2.0) * F.ln(F.greatest(uniform(f"{tag}/r", key), F.lit(TINY))))
    return radius * F.cos(F.lit(2 * math.pi) * uniform(f"{tag}/a", key))


def gaussian_sql(tag: str, key: str) -> str:
    return f"(sqrt(-2.0 * ln(greatest({uniform_sql(tag + '/r', key)}, {TINY!r}))) * cos({2 * math.pi!r} * {uniform_sql(tag + '/a', key)}))"


def gaussian_value(tag: str, key: object) -> float:
    r = math.sqrt(-2.0 * math.log(max(uniform_value(f"{tag}/r", key), TINY)))
    return r * math.cos(2 * math.pi * uniform_value(f"{tag}/a", key))


def cauchy(tag: str, key: Column) -> Column:
    return F.tan(F.lit(math.pi) * (uniform(tag, key) - F.lit(0.5)))


def cauchy_sql(tag: str, key: str) -> str:
    return f"tan({math.pi!r} * ({uniform_sql(tag, key)} - 0.5))"


def cauchy_value(tag: str, key: object) -> float:
    return math.tan(math.pi * (uniform_value(tag, key) - 0.5))
