"""Small networks as column expressions, for raters whose weights fit into a plan."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Weights that a plan takes as literals. Each reads its feature's whole expression, which the
#: optimizer puts in place, so larger networks go through Arrow.
MAX_LITERALS = 48


def dot(features: Column, weights: Sequence[float]) -> Column:
    total = F.lit(0.0)
    for i, w in enumerate(weights):
        total = total + features[i] * F.lit(float(w))
    return total


def sigmoid(x: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-x))


def linear(features: Column, weights: Sequence[float], bias: float = 0.0) -> Column:
    return dot(features, weights) + F.lit(float(bias))


def mlp(features: Column, w1: np.ndarray, b1: np.ndarray, w2: np.ndarray, b2: float) -> Column:
    """tanh hidden layer, linear output. w1: hidden x inputs."""
    if w1.size > MAX_LITERALS:
        raise ValueError("too many weights for a plan; score through Arrow")
    out = F.lit(float(b2))
    for row, b, v in zip(w1, b1, w2, strict=True):
        out = out + F.tanh(linear(features, row, b)) * F.lit(float(v))
    return out


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def inner(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))
