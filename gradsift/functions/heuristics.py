"""Single-metric scores of the baselines, for 8 x 8 rasters and for texts."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gradsift.functions.networks import sigmoid

SIDE = 8


def _cell(p: Column, r: int, c: int) -> Column:
    return p[r * SIDE + c]


def clarity(pixels: Column) -> Column:
    """Variance of the discrete Laplacian over inner cells."""
    inner = [
        _cell(pixels, r - 1, c) + _cell(pixels, r + 1, c) + _cell(pixels, r, c - 1) + _cell(pixels, r, c + 1) - F.lit(4.0) * _cell(pixels, r, c)
        for r in range(1, SIDE - 1) for c in range(1, SIDE - 1)
    ]
    cells = F.array(*inner)
    n = F.lit(float(len(inner)))
    mean = F.aggregate(cells, F.lit(0.0), lambda a, x: a + x) / n
    return F.aggregate(cells, F.lit(0.0), lambda a, x: a + x * x) / n - mean * mean


def _basis() -> np.ndarray:
    """Rows are the cosine basis vectors of a side."""
    k, i = np.meshgrid(np.arange(SIDE), np.arange(SIDE), indexing="ij")
    return np.where(k == 0, math.sqrt(1 / SIDE), math.sqrt(2 / SIDE)) * np.cos(math.pi * (2 * i + 1) * k / (2 * SIDE))


def frequency(pixels: Column, high: int = 8) -> Column:
    """Share of the energy in cosine coefficients whose indices sum to high or more.

    The constant term doesn't count; without other energy the share is 0. As an expression,
    64 coefficients of 64 cells are beyond what is compiled, so batches are multiplied.
    """

    @F.pandas_udf(T.DoubleType())
    def share(rows: pd.Series) -> pd.Series:
        known = rows.notna().to_numpy()
        out = pd.Series(np.full(len(rows), np.nan))
        if known.any():
            basis = _basis()
            cells = np.stack(rows[known].to_numpy()).astype(float).reshape(-1, SIDE, SIDE)
            energy = (basis @ cells @ basis.T) ** 2
            order = np.add.outer(np.arange(SIDE), np.arange(SIDE))
            top, rest = energy[:, order >= high].sum(axis=1), energy[:, (order > 0) & (order < high)].sum(axis=1)
            out[known] = np.where(top + rest > 1e-12, top / np.maximum(top + rest, 1e-300), 0.0)
        return out

    return share(pixels)


def edge_density(pixels: Column, tau: float = 0.1) -> Column:
    """Share of cells whose forward-difference gradient exceeds tau."""
    marks = F.lit(0)
    for r in range(SIDE - 1):
        for c in range(SIDE - 1):
            dx = _cell(pixels, r, c + 1) - _cell(pixels, r, c)
            dy = _cell(pixels, r + 1, c) - _cell(pixels, r, c)
            marks = marks + F.when(dx * dx + dy * dy > tau * tau, F.lit(1)).otherwise(F.lit(0))
    return marks / F.lit(float((SIDE - 1) ** 2))


#: Weights of the fixed estimator over standardised text statistics; a fitted one replaces them.
AESTHETIC = (0.2, -1.2, 0.9, -0.6, -0.2, -0.1)


def aesthetic(features: Column, weights: tuple[float, ...] = AESTHETIC, bias: float = 0.0) -> Column:
    """A linear estimator over pooled features, as a probability."""
    total = F.lit(float(bias))
    for i, w in enumerate(weights):
        total = total + features[i] * F.lit(w)
    return sigmoid(total)


def text_clarity(text: Column) -> Column:
    """Stand-in for texts: share of characters that aren't symbols."""
    t = F.coalesce(text, F.lit(""))
    n = F.char_length(t)
    return F.when(n > 0, F.char_length(F.translate(t, "#*$%&|<>", "")) / n).otherwise(F.lit(0.0))


def text_edges(text: Column) -> Column:
    """Stand-in for texts: share of line breaks and punctuation."""
    t = F.coalesce(text, F.lit(""))
    n = F.char_length(t)
    return F.when(n > 0, (n - F.char_length(F.translate(t, "\n.,;:!?", ""))) / n).otherwise(F.lit(0.0))


def rare_word_share(docs: DataFrame) -> DataFrame:
    """(doc_id, rare_share): the text stand-in of the frequency metric, the share of words that at most three documents have."""
    words = docs.select("doc_id", F.explode(F.filter(F.split(F.lower("text"), "[ \n]"), lambda w: w != "")).alias("w"))
    held = words.groupBy("doc_id", "w").agg(F.count(F.lit(1)).alias("n"))
    df = held.groupBy("w").agg(F.count(F.lit(1)).alias("df"))
    rare = F.sum(F.when(F.col("df") <= 3, F.col("n")).otherwise(0))
    return held.join(df, "w").groupBy("doc_id").agg((rare / F.sum("n")).alias("rare_share"))
