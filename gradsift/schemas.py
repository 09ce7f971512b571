"""Declared schemas and the binding of a table's columns to the method's roles."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

RATINGS = T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("score", T.DoubleType()), T.StructField("rank", T.LongType()), T.StructField("pct", T.DoubleType())])
TRACE = T.StructType(
    [T.StructField("sample_id", T.LongType()), T.StructField("step", T.IntegerType()), T.StructField("epoch", T.IntegerType()), T.StructField("loss", T.DoubleType()), T.StructField("grad_norm", T.DoubleType())]
)


@dataclass(frozen=True)
class SampleSpec:
    """Columns of a corpus by role; None where a role has none."""

    id: str
    features: str | None = None
    target: str | None = None
    text: str | None = None
    pixels: str | None = None
    shape: tuple[int, int] | None = None


def bind(df: DataFrame, spec: SampleSpec) -> DataFrame:
    """Only the spec's columns, so that scans read no others. Raises on a missing one."""
    wanted = [c for c in (spec.id, spec.features, spec.target, spec.text, spec.pixels) if c]
    missing = [c for c in wanted if c not in df.columns]
    if missing:
        raise ValueError(f"no columns {missing} in {df.columns}")
    return df.select(*wanted)


def validate_corpus(df: DataFrame, spec: SampleSpec, length: int | None = None) -> DataFrame:
    """One row: rows, null ids, repeated ids, null features, wrong lengths, features with NaN."""
    f = spec.features or spec.pixels
    aggs = [F.count(F.lit(1)).alias("n"), F.count_if(F.col(spec.id).isNull()).alias("null_ids")]
    if f:
        bad = F.lit(False) if length is None else F.size(f) != length
        aggs += [
            F.count_if(F.col(f).isNull()).alias("null_features"),
            F.count_if(F.col(f).isNotNull() & bad).alias("wrong_length"),
            F.count_if(F.exists(f, lambda x: F.isnan(x) | x.isNull())).alias("not_numbers"),
        ]
    repeated = df.groupBy(spec.id).agg(F.count(F.lit(1)).alias("c")).agg(F.coalesce(F.sum(F.col("c") - 1), F.lit(0)).alias("repeated_ids"))
    return df.agg(*aggs).crossJoin(F.broadcast(repeated))
