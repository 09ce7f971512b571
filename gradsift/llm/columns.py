"""Keeps a table's other columns out of the way of an operator's own."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_PREFIX = "_other_column_"


def hide(df: DataFrame, known: Iterable[str]) -> tuple[DataFrame, dict[str, str]]:
    """The table with all columns but the known renamed, and the names to give back."""
    known = set(known)
    back = {f"{_PREFIX}{i}": c for i, c in enumerate(df.columns) if c not in known}
    hidden = {c: h for h, c in back.items()}
    return df.select(*(F.col(f"`{c}`").alias(hidden.get(c, c)) for c in df.columns)), back


def give_back(df: DataFrame, back: dict[str, str]) -> DataFrame:
    return df.select(*(F.col(f"`{c}`").alias(back.get(c, c)) for c in df.columns))
