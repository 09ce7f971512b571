"""Cost and accuracy measures."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gradsift.functions.networks import inner, norm


def moments(df: DataFrame, features: str, d: int) -> DataFrame:
    """One row of means m0.. and population variances v0.. ."""
    f = F.col(features)
    return df.agg(*(F.avg(f[i]).alias(f"m{i}") for i in range(d)), *(F.var_pop(f[i]).alias(f"v{i}") for i in range(d)))


def frechet_diagonal(a: DataFrame, b: DataFrame, features: str, d: int) -> DataFrame:
    """Distance of Gaussians with diagonal covariances, as one row."""
    both = moments(a, features, d).crossJoin(moments(b, features, d).withColumnsRenamed({f"{k}{i}": f"{k}{i}_b" for k in "mv" for i in range(d)}))
    total = F.lit(0.0)
    for i in range(d):
        dm = F.col(f"m{i}") - F.col(f"m{i}_b")
        ds = F.sqrt(f"v{i}") - F.sqrt(f"v{i}_b")
        total = total + dm * dm + ds * ds
    return both.select(total.alias("frechet"))


def gram(df: DataFrame, features: str, d: int) -> tuple[int, np.ndarray, np.ndarray]:
    """Count, sum and Gram matrix in one scan; each task sends d x d numbers and they are added up."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total, second = 0, np.zeros(d), np.zeros((d, d))
        for batch in batches:
            x = np.array(batch.column(0).to_pylist(), dtype=float).reshape(-1, d)
            n += len(x)
            total += x.sum(axis=0)
            second += x.T @ x
        yield pa.RecordBatch.from_pydict({"i": np.arange(d * d + d + 1), "v": np.concatenate([[float(n)], total, second.ravel()])})

    rows = df.select(features).mapInArrow(partial, "i long, v double").groupBy("i").agg(F.sum("v").alias("v")).collect()
    v = np.zeros(d * d + d + 1)
    for r in rows:
        v[r["i"]] = r["v"]
    return int(v[0]), v[1 : d + 1], v[d + 1 :].reshape(d, d)


def frechet_distance(a: DataFrame, b: DataFrame, features: str, d: int, cov: str = "full") -> float:
    """Squared distance of the fitted Gaussians. The d x d root is taken on the driver."""
    if cov == "diag":
        return float(frechet_diagonal(a, b, features, d).first()[0])
    stats = []
    for df in (a, b):
        n, total, second = gram(df, features, d)
        mean = total / max(n, 1)
        stats.append((mean, second / max(n, 1) - np.outer(mean, mean)))
    (m, s), (k, t) = stats
    root = _root(s)
    return float(((m - k) ** 2).sum() + np.trace(s) + np.trace(t) - 2 * np.trace(_root(root @ t @ root)))


def _root(x: np.ndarray) -> np.ndarray:
    w, v = np.linalg.eigh((x + x.T) / 2)
    return (v * np.sqrt(np.maximum(w, 0))) @ v.T


def over(x: Column, n: Column) -> Column:
    """x / n of a norm n as IEEE 754 has it, where ANSI mode raises an error at 0: 0 / 0 is NaN."""
    return F.when(n == 0, x * F.lit(float("inf"))).otherwise(x / n)


def cosine(a: Column, b: Column) -> Column:
    """NaN where one is zero: such a pair has no angle, and its mean none either."""
    return over(over(inner(a, b), norm(a)), norm(b))


def alignment_score(pairs: DataFrame, a: str, b: str) -> DataFrame:
    return pairs.agg(F.avg(cosine(F.col(a), F.col(b))).alias("alignment"), F.count(F.lit(1)).alias("pairs"))


def compositional_score(selected: DataFrame, probes: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Share of probes of each kind whose terms are together in one selected text, and their mean.

    probes: probe_id, kind, terms (distinct). Texts are exploded to words once and meet the
    probes' terms, so only probe terms are exchanged.
    """
    terms = probes.select("probe_id", "kind", F.size("terms").alias("wanted"), F.explode("terms").alias("term"))
    words = selected.select(F.col(id_col).alias("_id"), F.explode(F.array_distinct(F.split(F.lower(F.coalesce(text_col, F.lit(""))), "[^a-z0-9]+"))).alias("term"))
    hits = words.join(terms, "term").groupBy("probe_id", "kind", "wanted", "_id").agg(F.count(F.lit(1)).alias("have")).where("have = wanted")
    passed = hits.select("probe_id").distinct().withColumn("_ok", F.lit(1))
    by_kind = probes.join(passed, "probe_id", "left").groupBy("kind").agg((F.count("_ok") / F.count(F.lit(1))).alias("pass_rate"))
    return by_kind.agg(F.avg("pass_rate").alias("compositional"), F.count(F.lit(1)).alias("kinds"))


def retention(selected: DataFrame, corpus: DataFrame) -> DataFrame:
    n = selected.agg(F.count(F.lit(1)).alias("images"))
    return n.crossJoin(corpus.agg(F.count(F.lit(1)).alias("corpus"))).withColumn("retention", F.col("images") / F.col("corpus"))


def training_cost(selected: DataFrame, epochs: int, seconds_per_visit: float) -> DataFrame:
    n = selected.agg(F.count(F.lit(1)).alias("images"))
    return n.select("images", (F.col("images") * epochs).alias("visits"), (F.col("images") * epochs * F.lit(seconds_per_visit) / 3600).alias("hours"))


def time_to_target(curves: DataFrame, base: str, lower_is_better: bool = True) -> DataFrame:
    """Per other method: the base's best value, when each first reaches it, and the ratio of the times.

    curves: method, elapsed, value.
    """
    w = Window.partitionBy("method").orderBy("elapsed").rowsBetween(Window.unboundedPreceding, 0)
    best = F.min if lower_is_better else F.max
    running = curves.withColumn("_best", best("value").over(w))
    goal = curves.where(F.col("method") == base).agg(best("value").alias("target"))
    reached = running.crossJoin(F.broadcast(goal)).where(F.col("_best") <= F.col("target") if lower_is_better else F.col("_best") >= F.col("target"))
    first = reached.groupBy("method", "target").agg(F.min("elapsed").alias("elapsed"))
    of_base = first.where(F.col("method") == base).select(F.col("elapsed").alias("base_elapsed"))
    return first.where(F.col("method") != base).crossJoin(F.broadcast(of_base)).select("method", "target", "elapsed", "base_elapsed", (F.col("base_elapsed") / F.col("elapsed")).alias("speedup"))


def dynamics_by_range(trace: DataFrame, ranked: DataFrame, id_col: str, bins: int = 10) -> DataFrame:
    """Per percentile bin: mean loss and norm, their slopes over epochs, and the first minus the last norm."""
    q = F.least(F.floor(F.col("pct") * bins), F.lit(bins - 1)).cast("int").alias("bin")
    per_epoch = trace.join(ranked.select(id_col, "pct"), id_col).groupBy(q, "epoch").agg(F.avg("loss").alias("loss"), F.avg("grad_norm").alias("norm"))
    return per_epoch.groupBy("bin").agg(
        F.avg("loss").alias("mean_loss"), F.avg("norm").alias("mean_norm"),
        F.regr_slope("loss", "epoch").alias("loss_slope"), F.regr_slope("norm", "epoch").alias("norm_slope"),
        (F.max_by("norm", F.col("epoch")) - F.min_by("norm", F.col("epoch"))).alias("norm_change"),
    )


def sample_across_ranges(ranked: DataFrame, per_bin: int, id_col: str, bins: int = 10, seed: int = 42) -> DataFrame:
    """per_bin samples of each percentile bin, by hash.

    A first cut of each bin by hash keeps about four times what is wanted (all, if fewer), so
    the window that picks exactly sees a number of rows that doesn't grow with the corpus.
    """
    from gradsift.functions.hashing import hash_uniform

    q = F.least(F.floor(F.col("pct") * bins), F.lit(bins - 1)).cast("int")
    keyed = ranked.withColumn("bin", q).withColumn("_u", hash_uniform(id_col, seed))
    room = keyed.groupBy("bin").agg(F.count(F.lit(1)).alias("_n"))
    near = keyed.join(F.broadcast(room), "bin").where(F.col("_u") * F.col("_n") < 4.0 * per_bin + 40)
    w = Window.partitionBy("bin").orderBy("_u", id_col)
    return near.withColumn("_nth", F.row_number().over(w)).where(F.col("_nth") <= per_bin).drop("_nth", "_u", "_n")


def delta_vs_random(results: DataFrame, base: str = "random") -> DataFrame:
    """results: method, k, metric, value; adds delta to the base at the same k and metric."""
    of_base = results.where(F.col("method") == base).select("k", "metric", F.col("value").alias("base_value"))
    return results.join(of_base, ["k", "metric"]).withColumn("delta", F.col("value") - F.col("base_value"))


def auc(scored: DataFrame, score: str, label: str) -> DataFrame:
    """Area under the ROC curve by rank sums, equal scores at their mean rank."""
    by = scored.groupBy(F.col(score).alias("_s")).agg(F.count(F.lit(1)).alias("_n"), F.sum(F.col(label).cast("long")).alias("_pos"))
    from gradsift.operators.ranking import bins_for, splitters, with_bin

    cuts = splitters(by, "_s", bins_for(scored.count()))
    binned = with_bin(by, "_s", cuts)
    bins = binned.groupBy("_bin").agg(F.sum("_n").alias("_total"))
    before = bins.withColumn("_before", F.coalesce(F.sum("_total").over(Window.orderBy("_bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("_bin", "_before")
    w = Window.partitionBy("_bin").orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)
    ranked = binned.withColumn("_below", F.coalesce(F.sum("_n").over(w), F.lit(0))).join(F.broadcast(before), "_bin")
    mean_rank = F.col("_before") + F.col("_below") + (F.col("_n") + 1) / 2
    sums = ranked.agg(F.sum(mean_rank * F.col("_pos")).alias("r"), F.sum("_pos").alias("p"), F.sum("_n").alias("n"))
    neg = F.col("n") - F.col("p")
    return sums.select(((F.col("r") - F.col("p") * (F.col("p") + 1) / 2) / (F.col("p") * neg)).alias("auc"), F.col("p").alias("positives"), neg.alias("negatives"))


def selection_overlap(a: DataFrame, b: DataFrame, id_col: str) -> DataFrame:
    left, right = a.select(id_col).withColumn("_a", F.lit(1)), b.select(id_col).withColumn("_b", F.lit(1))
    both = F.count_if(F.col("_a").isNotNull() & F.col("_b").isNotNull())
    return left.join(right, id_col, "full").agg(both.alias("both"), F.count(F.lit(1)).alias("either"), (both / F.count(F.lit(1))).alias("jaccard"))


def curve_stability(curves: DataFrame) -> DataFrame:
    """Per method: changes of direction, and the largest rise above the best value so far (lower is better)."""
    w = Window.partitionBy("method").orderBy("epoch")
    stepped = curves.withColumn("_d", F.col("value") - F.lag("value").over(w)).withColumn("_best", F.min("value").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    turned = stepped.withColumn("_turn", F.when(F.signum("_d") * F.signum(F.lag("_d").over(w)) < 0, 1).otherwise(0))
    return turned.groupBy("method").agg(F.sum("_turn").alias("turns"), F.max(F.col("value") - F.col("_best")).alias("drawdown"))


def selection_gain(subset_value: DataFrame, full_value: DataFrame, lower_is_better: bool = True, tolerance: float = 0.0) -> DataFrame:
    """Two one-row frames with value: the gap, and whether the subset is better or as good."""
    both = subset_value.select(F.col("value").alias("subset")).crossJoin(full_value.select(F.col("value").alias("whole")))
    gap = (F.col("whole") - F.col("subset")) if lower_is_better else (F.col("subset") - F.col("whole"))
    return both.withColumn("gap", gap).withColumn("holds", F.col("gap") >= -tolerance)
