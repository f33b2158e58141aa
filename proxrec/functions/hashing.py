"""Fractions that are a pure function of keys, equal in Spark and DuckDB."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def fraction(seed: int, *keys: str) -> Column:
    """First 8 hex digits of md5(seed|key|...) as a share of 2**32."""
    joined = F.concat_ws("|", F.lit(str(seed)), *[F.col(k).cast("string") for k in keys])
    return F.conv(F.substring(F.md5(joined), 1, 8), 16, 10).cast("double") / float(1 << 32)


def fraction_sql(seed: int, *keys: str) -> str:
    joined = " || '|' || ".join([f"'{seed}'", *[f"CAST({k} AS VARCHAR)" for k in keys]])
    return f"(('0x' || substr(md5({joined}), 1, 8))::BIGINT / 4294967296.0)"
