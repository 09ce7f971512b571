"""Sample weights: softmax in the batch, batch descriptors and weights, their product, ratings."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gradsift.functions.networks import linear, sigmoid


def softmax_in_batch(df: DataFrame, score: str, batch: str = "batch_id", out: str = "inst_weight") -> DataFrame:
    """Weights that sum to 1 in each batch; the batch's largest score is subtracted first."""
    w = Window.partitionBy(batch)
    shifted = df.withColumn("_e", F.exp(F.col(score) - F.max(score).over(w)))
    return shifted.withColumn(out, F.col("_e") / F.sum("_e").over(w)).drop("_e")


def batch_descriptor(df: DataFrame, features: str, d: int, batch: str = "batch_id") -> DataFrame:
    """(batch, descriptor): the features' means, then their population variances."""
    f = F.col(features)
    aggs = [F.avg(f[i]).alias(f"m{i}") for i in range(d)] + [F.var_pop(f[i]).alias(f"v{i}") for i in range(d)]
    return df.groupBy(batch).agg(*aggs).select(batch, F.array(*(F.col(f"{k}{i}") for k in "mv" for i in range(d))).alias("descriptor"))


def group_weight(descriptors: DataFrame, hidden: Sequence[Sequence[float]], hidden_bias: Sequence[float], out_weights: Sequence[float], out_bias: float) -> DataFrame:
    """Adds batch_weight in (0, 1): two layers over the descriptor, sigmoid at the end."""
    z = F.lit(float(out_bias))
    for row, b, v in zip(hidden, hidden_bias, out_weights, strict=True):
        z = z + F.tanh(linear(F.col("descriptor"), row, b)) * F.lit(float(v))
    return descriptors.withColumn("batch_weight", sigmoid(z))


def combine_weights(rows: DataFrame, batches: DataFrame | None, batch: str = "batch_id") -> DataFrame:
    """Adds weight: instance weight times batch weight, or the instance weight alone."""
    if batches is None:
        return rows.withColumn("weight", F.col("inst_weight"))
    return rows.join(batches.select(batch, "batch_weight"), batch).withColumn("weight", F.col("inst_weight") * F.col("batch_weight"))


def rate(df: DataFrame, raw: str, mode: str = "logit", batches: DataFrame | None = None, batch: str = "batch_id") -> DataFrame:
    """Adds score. logit: the raw score, map-only; weight: the product in fixed batches;
    logit_group: the raw score and the log of the batch weight."""
    if mode == "logit":
        return df.withColumn("score", F.col(raw))
    if mode == "weight":
        return combine_weights(softmax_in_batch(df, raw, batch), batches, batch).withColumn("score", F.col("weight"))
    if mode == "logit_group":
        return df.join(batches.select(batch, "batch_weight"), batch).withColumn("score", F.col(raw) + F.log("batch_weight"))
    raise ValueError(f"no score mode {mode!r}")


def combine_scores(df: DataFrame, scores: Sequence[str], id_col: str) -> DataFrame:
    """Mean of the scores' percentiles, each ranked over the corpus. The scores are written once, since each ranking reads them."""
    from gradsift.operators.ranking import rank_corpus
    from gradsift.sources.staging import staged

    df, total = staged(df, "scores"), F.lit(0.0)
    for s in scores:
        df = rank_corpus(df, s, id_col).withColumnRenamed("pct", f"_pct_{s}").drop("rank")
        total = total + (F.lit(1.0) - F.col(f"_pct_{s}"))
    return df.withColumn("combined", total / F.lit(float(len(scores)))).drop(*(f"_pct_{s}" for s in scores))
