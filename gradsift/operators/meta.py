"""One step of each part of the meta-gradient method, over DataFrames.

The proxy is a linear regression and the rater linear in the features, so each step is one
aggregation whose result has the size of the parameters. These steps are exact and serve as
the reference for the vectorised engine in plans.training.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradsift.functions.networks import linear, sigmoid
from gradsift.operators.proxies import gradient_total, linear_loss
from gradsift.operators.rating import batch_descriptor, softmax_in_batch


def weigh(df: DataFrame, mu: Sequence[float], d: int, group: Sequence[float] | None = None, batch: str = "batch_id") -> DataFrame:
    """Adds inst_weight, batch_weight (1 without a group part) and weight.

    mu: d weights and a bias; group: 2d weights over the batch descriptor, and a bias.
    """
    scored = softmax_in_batch(df.withColumn("raw_score", linear(F.col("features"), mu[:d], mu[d])), "raw_score", batch)
    if group is None:
        return scored.withColumn("batch_weight", F.lit(1.0)).withColumn("weight", F.col("inst_weight"))
    b = batch_descriptor(df, "features", d, batch).select(batch, sigmoid(linear(F.col("descriptor"), group[: 2 * d], group[2 * d])).alias("batch_weight"))
    return scored.join(b, batch).withColumn("weight", F.col("inst_weight") * F.col("batch_weight"))


def warm_up(train: DataFrame, theta: Sequence[float], steps: int, rate: float) -> list[list[float]]:
    """Parameters after each of the steps on training data alone, unweighted."""
    out = [list(theta)]
    for _ in range(steps):
        g = gradient_total(train, "features", "target", out[-1], reduction="mean")
        out.append([t - rate * x for t, x in zip(out[-1], g, strict=True)])
    return out


def reference_step(weighted: DataFrame, theta: Sequence[float], rate: float, weighting: str = "rater") -> list[float]:
    g = gradient_total(weighted, "features", "target", theta, "weight" if weighting == "rater" else None, "sum" if weighting == "rater" else "mean")
    return [t - rate * x for t, x in zip(theta, g, strict=True)]


def joint_step(weighted: DataFrame, validation: DataFrame, theta: Sequence[float], rate: float) -> list[float]:
    """Against the sum of the mean validation gradient and the weighted training gradient."""
    g = gradient_total(weighted, "features", "target", theta, "weight", "sum")
    v = gradient_total(validation, "features", "target", theta, None, "mean")
    return [t - rate * (x + y) for t, x, y in zip(theta, g, v, strict=True)]


def multipliers(weighted: DataFrame, theta: Sequence[float], theta_hat: Sequence[float] | None, rule: str = "gap") -> DataFrame:
    """Adds mult: the loss gap of the two proxies, or the primary's loss."""
    f, y = F.col("features"), F.col("target")
    loss = linear_loss(f, y, theta)
    if rule == "gap":
        return weighted.withColumn("mult", loss - linear_loss(f, y, theta_hat))
    if rule == "loss":
        return weighted.withColumn("mult", loss)
    raise ValueError(f"no rule {rule!r}")


def rater_gradient(marked: DataFrame, d: int, batch: str = "batch_id") -> DataFrame:
    """Per batch: the gradient of the sum of mult x weight for the rater's weights and bias.

    With instance weights a, batch weight b and mean multiplier m, the raw score of sample j
    has the gradient b a_j (mult_j - m), which sums to 0 over the batch.
    """
    mean = marked.groupBy(batch).agg(F.sum(F.col("inst_weight") * F.col("mult")).alias("mean_mult"))
    each = marked.join(mean, batch).withColumn("_g", F.col("batch_weight") * F.col("inst_weight") * (F.col("mult") - F.col("mean_mult")))
    return each.groupBy(batch).agg(
        F.first("mean_mult").alias("mean_mult"), F.first("batch_weight").alias("batch_weight"),
        *(F.sum(F.col("_g") * F.col("features")[i]).alias(f"g{i}") for i in range(d)), F.sum("_g").alias("g_bias"),
    )


def rater_step(marked: DataFrame, mu: Sequence[float], d: int, alpha: float, batch: str = "batch_id") -> list[float]:
    """One descent step on the mean of the batches' gradients."""
    g = rater_gradient(marked, d, batch)
    row = g.agg(*(F.avg(c).alias(c) for c in [*(f"g{i}" for i in range(d)), "g_bias"])).first()
    return [m - alpha * (x or 0.0) for m, x in zip(mu, row, strict=True)]


def check_overparameterised(losses: DataFrame, loss: str, eps: float, n_params: int) -> DataFrame:
    """One row: mean loss, share under eps, parameters a sample, and the rule that this speaks for."""
    out = losses.agg(
        F.avg(loss).alias("mean_loss"), (F.count_if(F.col(loss) < eps) / F.count(F.lit(1))).alias("share_under"),
        (F.lit(float(n_params)) / F.count(F.lit(1))).alias("params_per_sample"),
    )
    near_zero = (F.col("share_under") >= 0.95) & (F.col("params_per_sample") >= 1)
    return out.withColumn("rule", F.when(near_zero, F.lit("loss")).otherwise(F.lit("gap")))


def solve_bilevel_grid(train: DataFrame, validation: DataFrame, grid: DataFrame) -> DataFrame:
    """The exact solution for a grid of raters exp(c x), of a one-feature regression.

    train, validation: x, y. grid: candidate, c. Each candidate's weighted least squares has
    a closed form, so one aggregation solves all inner problems and another evaluates them.
    """
    w = F.exp(F.col("c") * F.col("x"))
    inner = (
        train.crossJoin(F.broadcast(grid)).groupBy("candidate", "c")
        .agg(F.sum(w * F.col("x") * F.col("y")).alias("_xy"), F.sum(w * F.col("x") * F.col("x")).alias("_xx"))
        .select("candidate", "c", (F.col("_xy") / F.col("_xx")).alias("theta"))
    )
    r = F.col("theta") * F.col("x") - F.col("y")
    outer = validation.crossJoin(F.broadcast(inner)).groupBy("candidate", "c", "theta").agg(F.avg(F.lit(0.5) * r * r).alias("val_loss"))
    best = outer.agg(F.min(F.struct("val_loss", "candidate")).alias("_b"))
    return outer.crossJoin(F.broadcast(best)).withColumn("best", F.col("candidate") == F.col("_b.candidate")).drop("_b")
