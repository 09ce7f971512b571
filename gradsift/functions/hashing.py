"""Deterministic pseudo-random columns. The same in any engine with md5, and under retries."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash32(id_col: Column | str, seed: int) -> Column:
    """The first 32 bits of md5("seed:id")."""
    name = F.concat(F.lit(f"{seed}:"), F.col(id_col).cast("string") if isinstance(id_col, str) else id_col.cast("string"))
    return F.conv(F.substring(F.md5(name.cast("binary")), 1, 8), 16, 10).cast("long")


def hash_uniform(id_col: Column | str, seed: int) -> Column:
    """In (0, 1)."""
    return (hash32(id_col, seed) + F.lit(0.5)) / F.lit(4294967296.0)
