"""Python functions for what column expressions can't say, and SQL functions that they can."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def mlp_score(w1: np.ndarray, b1: np.ndarray, w2: np.ndarray, b2: float):
    """A pandas UDF of a network too large for an expression: features -> score."""

    @F.pandas_udf(T.DoubleType())
    def score(features: pd.Series) -> pd.Series:
        if not len(features):
            return pd.Series([], dtype=float)
        x = np.stack(features.to_numpy())
        return pd.Series(np.tanh(x @ w1.T + b1) @ w2 + b2)

    return score


@F.pandas_udf(T.DoubleType())
def second_moment(v: pd.Series) -> float:
    """Grouped aggregate: mean of squares."""
    return float((v.astype(float) ** 2).mean())


@F.udtf(returnType=T.StructType().add("pos", T.IntegerType()).add("gram", T.StringType()))
class ExplodeNgrams:
    """Word n-grams of a text, with their places. A null text has none."""

    def eval(self, text: str, n: int) -> Iterator[tuple[int, str]]:
        words = (text or "").split(" ")
        for i in range(len(words) - n + 1):
            yield i, " ".join(words[i : i + n])


@F.udtf(returnType=T.StructType().add("step", T.IntegerType()).add("rate", T.DoubleType()))
class UnrollSteps:
    """Step numbers and learning rates of a schedule base / (1 + decay k). A null number of steps has none."""

    def eval(self, steps: int | None, base: float, decay: float) -> Iterator[tuple[int, float]]:
        for k in range(steps or 0):
            yield k, base / (1 + decay * k)


def register_linear(spark: SparkSession, name: str, weights: Sequence[float], bias: float = 0.0) -> None:
    """A SQL function of a linear rater; the optimizer inlines its body."""
    body = " + ".join(f"features[{i}] * {float(w)!r}D" for i, w in enumerate(weights))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(features ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body} + {float(bias)!r}D")


def register_tables(spark: SparkSession) -> None:
    spark.udtf.register("explode_ngrams", ExplodeNgrams)
    spark.udtf.register("unroll_steps", UnrollSteps)
