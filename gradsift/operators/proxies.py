"""Proxy models with closed-form losses and gradients per sample, as DataFrame operations."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradsift.functions.features import pool_raster
from gradsift.functions.hashing import hash_uniform
from gradsift.functions.networks import dot, sigmoid

# linear regression


def linear_residual(features: Column, target: Column, theta: Sequence[float]) -> Column:
    return dot(features, theta) - target


def linear_loss(features: Column, target: Column, theta: Sequence[float]) -> Column:
    r = linear_residual(features, target, theta)
    return F.lit(0.5) * r * r


def linear_gradient(features: Column, target: Column, theta: Sequence[float]) -> Column:
    r = linear_residual(features, target, theta)
    return F.array(*(r * features[i] for i in range(len(theta))))


def gradient_total(df: DataFrame, features: str, target: str, theta: Sequence[float], weight: str | None = None, reduction: str = "sum") -> list[float]:
    """The (weighted) gradient over all rows: one aggregation, len(theta) numbers to the driver."""
    r = linear_residual(F.col(features), F.col(target), theta)
    w = F.col(weight) if weight else F.lit(1.0)
    how = F.sum if reduction == "sum" else F.avg
    row = df.agg(*(how(w * r * F.col(features)[i]).alias(f"g{i}") for i in range(len(theta)))).first()
    return [x or 0.0 for x in row]


# logistic classifier


def logistic_loss(features: Column, label: Column, theta: Sequence[float]) -> Column:
    z = dot(features, theta)
    return F.greatest(z, F.lit(0.0)) - z * label + F.log1p(F.exp(-F.abs(z)))


def logistic_gradient(features: Column, label: Column, theta: Sequence[float]) -> Column:
    r = sigmoid(dot(features, theta)) - label
    return F.array(*(r * features[i] for i in range(len(theta))))


# autoregressive bigram model, in long form


def row_normaliser(logits: DataFrame) -> DataFrame:
    """(a, lse): log of the sum of exponentials of a row of logits (a, b, value)."""
    top = logits.groupBy("a").agg(F.max("value").alias("_top"))
    return logits.join(top, "a").groupBy("a", "_top").agg(F.sum(F.exp(F.col("value") - F.col("_top"))).alias("_s")).select("a", (F.log("_s") + F.col("_top")).alias("lse"))


def bigram_loss(counts: DataFrame, logits: DataFrame, id_col: str) -> DataFrame:
    """(id, n, loss): mean negative log-likelihood of a sample's transitions. The logits are broadcast: V^2 rows."""
    table = logits.join(row_normaliser(logits), "a").select("a", "b", (F.col("lse") - F.col("value")).alias("nll"))
    return (
        counts.join(F.broadcast(table), ["a", "b"]).groupBy(id_col)
        .agg(F.sum("n").alias("n"), (F.sum(F.col("n") * F.col("nll")) / F.sum("n")).alias("loss"))
    )


def bigram_gradient(counts: DataFrame, logits: DataFrame, id_col: str, weights: DataFrame | None = None) -> DataFrame:
    """(a, b, grad): the mean, or the weighted sum, of the samples' gradients.

    Only the V^2 transition totals are exchanged, not a gradient for each sample.
    """
    sizes = counts.groupBy(id_col).agg(F.sum("n").alias("_n"))
    if weights is None:
        total = sizes.agg(F.count(F.lit(1)).alias("_samples"))
        scaled = counts.join(sizes, id_col).crossJoin(F.broadcast(total)).withColumn("_w", F.col("n") / F.col("_n") / F.col("_samples"))
    else:
        scaled = counts.join(sizes.join(weights, id_col), id_col).withColumn("_w", F.col("n") / F.col("_n") * F.col("weight"))
    cells = scaled.groupBy("a", "b").agg(F.sum("_w").alias("c"))
    rows = cells.groupBy("a").agg(F.sum("c").alias("_row"))
    prob = logits.join(row_normaliser(logits), "a").select("a", "b", F.exp(F.col("value") - F.col("lse")).alias("_p"))
    return (
        prob.join(rows, "a").join(cells, ["a", "b"], "left")
        .select("a", "b", (F.col("_row") * F.col("_p") - F.coalesce("c", F.lit(0.0))).alias("grad"))
    )


# next-scale predictor over an 8 x 8 raster


def pyramid(pixels: Column) -> dict[int, Column]:
    """Mean pools with 1, 2, 4 and 8 cells a side."""
    return {1: pool_raster(pixels, 8, 1), 2: pool_raster(pixels, 8, 2), 4: pool_raster(pixels, 8, 4), 8: pixels}


def upsample(cells: Column, side: int) -> Column:
    """Each cell repeated to two by two."""
    big = 2 * side
    return F.array(*(cells[(r // 2) * side + c // 2] for r in range(big) for c in range(big)))


def _errors(guess: Column, truth: Column, w: Column) -> Column:
    return F.zip_with(guess, truth, lambda g, t: (w * g - t) * (w * g - t))


def scale_loss(pixels: Column, coefficients: Sequence[float] = (1.0, 1.0, 1.0)) -> Column:
    """Mean over scales of the mean squared error from the scale before, upsampled and scaled."""
    levels, total = pyramid(pixels), F.lit(0.0)
    for k, w in zip((1, 2, 4), coefficients, strict=True):
        guess, truth = upsample(levels[k], k), levels[2 * k]
        total = total + F.aggregate(_errors(guess, truth, F.lit(float(w))), F.lit(0.0), lambda a, x: a + x) / F.lit(float(4 * k * k))
    return total / F.lit(3.0)


# denoiser with a noise level


def denoise_loss(pixels: Column, id_col: str, level: int, levels: int = 10, seed: int = 42) -> Column:
    """Squared error of the best linear denoiser of unit-norm rasters at a noise level.

    Noise is a hash of the id and the cell, so that it is the same whenever it is asked for.
    """
    t = (level + 1) / levels
    shrink = (1 - t) ** 2 / ((1 - t) ** 2 + t**2 * 64)
    noisy = F.transform(pixels, lambda x, i: (x * F.lit(1 - t) + F.lit(t) * (hash_uniform(F.concat(F.col(id_col).cast("string"), F.lit(":"), i.cast("string")), seed) - 0.5)))
    errors = F.zip_with(noisy, pixels, lambda z, x: (F.lit(shrink) * z - x) * (F.lit(shrink) * z - x))
    return F.aggregate(errors, F.lit(0.0), lambda a, x: a + x)
