"""Randomness that Spark, DuckDB and NumPy agree on, and that a retried task repeats."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def portable_hash(a, b, seed) -> Column:
    """The first 8 hex digits of md5('a:b:seed') as BIGINT."""
    text = F.concat_ws(":", *[(x if isinstance(x, Column) else F.lit(x)).cast("string") for x in (a, b, seed)])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("bigint")


def portable_hash_sql(a, b, seed) -> str:
    """The same in DuckDB."""
    return f"('0x' || substr(md5(concat({a}, ':', {b}, ':', {seed})), 1, 8))::BIGINT"


def portable_hash_py(a, b, seed) -> int:
    return int(hashlib.md5(f"{a}:{b}:{seed}".encode()).hexdigest()[:8], 16)


def dyadic_weight(layer, row, col, seed: int = 7) -> Column:
    """Multiples of 1/16 in [-1, 1]: their sums are exact, so that no summation order shows."""
    return (portable_hash(layer.cast("bigint") * 1000003 + row, col, seed) % 33 - 16) / F.lit(16.0)


def dyadic_weight_sql(layer: str, row: str, col: str, seed: int = 7) -> str:
    return f"(({portable_hash_sql(f'({layer})::BIGINT * 1000003 + {row}', col, seed)} % 33 - 16) / 16.0::DOUBLE)"


def uniform_weight(layer, row, col, seed: int = 7) -> Column:
    """Uniform in [-1, 1): the production form, on Spark's own hash."""
    return F.pmod(F.xxhash64(layer, row, col, F.lit(seed)), F.lit(1 << 53)) / F.lit(float(1 << 52)) - 1
