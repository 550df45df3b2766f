"""Uniform numbers from keys, the same in any layout and in other SQL engines."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(seed: str, *keys) -> Column:
    """A number in [0, 1) from the first 32 bits of an MD5 of seed and keys."""
    text = F.concat_ws("|", F.lit(seed), *(F.col(k).cast("string") if isinstance(k, str) else k.cast("string") for k in keys))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def uniform_sql(seed: str, *keys: str) -> str:
    """The same number in DuckDB's SQL."""
    return f"(('0x' || substr(md5(concat_ws('|', '{seed}', {', '.join(keys)})), 1, 8))::BIGINT / 4294967296.0)"
