"""Reproducible draws: a hash of key and salt instead of a random generator, equal on every retry and in SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def u(key: Column, salt: str) -> Column:
    """Uniform in [0, 1) from the first 32 bits of md5."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", key.cast("string"), F.lit(salt))), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def u_sql(key: str, salt: str) -> str:
    """The same draw in DuckDB."""
    return f"(('0x' || substr(md5({key}::VARCHAR || ':{salt}'), 1, 8))::BIGINT / 4294967296.0)"
