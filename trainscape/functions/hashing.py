"""Hashes that agree between engines, processes and partitionings."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 2**32


def portable_hash(salt: str, *keys: str | Column) -> Column:
    """The first 32 bits of md5 over salt and keys joined by '|', as a long."""
    text = F.concat_ws("|", F.lit(salt), *((F.col(k) if isinstance(k, str) else k).cast("string") for k in keys))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def unit_hash(salt: str, *keys: str | Column) -> Column:
    """The portable hash as a number in [0, 1)."""
    return portable_hash(salt, *keys) / F.lit(float(SPAN))


def hash_sql(salt: str, *keys: str) -> str:
    """The portable hash in DuckDB's SQL."""
    return f"('0x' || substr(md5(concat_ws('|', '{salt}', {', '.join(keys)})), 1, 8))::ubigint::bigint"
