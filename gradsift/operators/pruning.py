"""Subset selection over ranked samples: top-K, blocks, Gaussians over the percentile, random.

Defined results: an empty ranking gives empty selections; equal keys are taken by id; more
rows than there are is an error; rows that repeat an id are drawn alike. Other columns pass.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gradsift.functions.hashing import hash_uniform
from gradsift.operators.ranking import bins_for, select_smallest, unused


@dataclass(frozen=True)
class ShiftedGaussian:
    """Discards the best-ranked share, then weighs percentiles around a mean past the middle."""

    discard: float = 0.20
    mean: float = 0.60
    spread: float = 0.20

    def __post_init__(self) -> None:
        if self.spread <= 0:
            raise ValueError("the spread must be positive")
        if not 0 <= self.discard < 1:
            raise ValueError("the discarded share must be in [0, 1)")


CENTRED = ShiftedGaussian(discard=0.0, mean=0.5, spread=0.20)


def density(pct: Column, cfg: ShiftedGaussian) -> Column:
    d = pct - F.lit(cfg.mean)
    return F.when(pct < cfg.discard, F.lit(0.0)).otherwise(F.exp(-(d * d) / F.lit(2 * cfg.spread * cfg.spread)))


def gaussian_density(ranked: DataFrame, cfg: ShiftedGaussian) -> DataFrame:
    """Adds g, and p, which sums to 1: one aggregate, broadcast as one row."""
    g = ranked.withColumn("g", density(F.col("pct"), cfg))
    total = g.agg(F.sum("g").alias("_total"))
    return g.crossJoin(F.broadcast(total)).withColumn("p", F.col("g") / F.col("_total")).drop("_total")


def prune_none(ranked: DataFrame) -> DataFrame:
    return ranked


def prune_top_k(ranked: DataFrame, k: int) -> DataFrame:
    return ranked.where(F.col("rank") <= k)


def prune_block(ranked: DataFrame, start: float, ratio: float) -> DataFrame:
    return ranked.where((F.col("pct") >= start) & (F.col("pct") < start + ratio - 1e-12))


def prune_trimmed(ranked: DataFrame, ratio: float) -> DataFrame:
    """Both ends dropped alike."""
    side = (1 - ratio) / 2
    return prune_block(ranked, side, ratio)


def prune_random(df: DataFrame, k: int, id_col: str, seed: int = 42) -> DataFrame:
    u = unused(df, "_u")[0]
    return select_smallest(df.withColumn(u, hash_uniform(id_col, seed)), u, k, id_col).drop(u)


def prune_shifted_gaussian(ranked: DataFrame, k: int, id_col: str, cfg: ShiftedGaussian = ShiftedGaussian(), sampler: str = "exact", seed: int = 42, n_bins: int = 100) -> DataFrame:
    """About or exactly k samples with probability after the Gaussian.

    exact: exponential keys, the k smallest, so a larger k keeps what a smaller one has.
    quota: the expected number of each percentile bin, by hash order within it.
    poisson: each sample on its own with probability min(1, c g), c from the bins; the size
    varies with a deviation of at most sqrt(k), and the filter needs no exchange.
    """
    g, u, e, q, part, nth, take, cut = unused(ranked, "_g", "_u", "_e", "_q", "_part", "_nth", "_take", "_cut")
    live = ranked.where(F.col("pct") >= cfg.discard).withColumn(g, density(F.col("pct"), cfg)).withColumn(u, hash_uniform(id_col, seed))
    if sampler == "exact":
        keyed = live.where(F.col(g) > 0).withColumn(e, -F.log(u) / F.when(F.col(g) > 0, F.col(g)))
        return select_smallest(keyed, e, k, id_col).drop(g, u, e)
    bins = live.withColumn(q, F.floor(F.col("pct") * n_bins).cast("int"))
    rows = {r["q"]: (r["n"], r["g"]) for r in bins.groupBy(F.col(q).alias("q")).agg(F.count(F.lit(1)).alias("n"), F.sum(g).alias("g")).collect()}
    total = sum(n for n, _ in rows.values())
    if k > total:
        raise ValueError(f"{k} samples wanted of {total} that are left")
    if sampler == "quota":
        quota = water_fill({b: w for b, (_, w) in rows.items()}, {b: n for b, (n, _) in rows.items()}, k)
        # of a bin, parts by hash below that in which the quota ends are kept unsorted
        n_parts = min(1000, bins_for(-(-total // n_bins)))
        parted = bins.withColumn(part, F.floor(F.col(u) * n_parts).cast("int"))
        counts: dict[int, dict[int, int]] = {}
        for r in parted.groupBy(F.col(q).alias("q"), F.col(part).alias("p")).count().collect():
            counts.setdefault(r["q"], {})[r["p"]] = r["count"]
        table = ranked.sparkSession.createDataFrame([(b, *_edge(counts[b], quota[b])) for b in sorted(counts)], f"`{q}` int, `{cut}` int, `{take}` long")
        placed = parted.join(F.broadcast(table), q)
        edge = placed.where(F.col(part) == F.col(cut)).withColumn(nth, F.row_number().over(Window.partitionBy(q).orderBy(u, F.col(f"`{id_col}`"))))
        whole = placed.where(F.col(part) < F.col(cut))
        return whole.unionByName(edge.where(F.col(nth) <= F.col(take)).drop(nth)).drop(g, u, q, part, cut, take)
    if sampler == "poisson":
        c = inclusion_scale([(n, w / n) for n, w in rows.values()], k)
        return live.where(F.col(u) < F.least(F.lit(1.0), F.lit(c) * F.col(g))).drop(g, u)
    raise ValueError(f"no sampler {sampler!r}")


def _edge(parts: dict[int, int], k: int) -> tuple[int, int]:
    """The part in which the k-th row lies, and the rows to take from it."""
    for p in sorted(parts):
        if k <= parts[p]:
            return p, k
        k -= parts[p]
    return max(parts) + 1, 0


def water_fill(weight: dict[int, float], room: dict[int, int], k: int) -> dict[int, int]:
    """Whole quotas in proportion to weight, none above its room, k in all."""
    out, open_, left = dict.fromkeys(weight, 0), set(weight), k
    share: dict[int, float] = {}
    while left > 0 and open_:
        total = sum(weight[q] for q in open_)
        share = {q: left * weight[q] / total for q in open_}
        full = [q for q in open_ if share[q] >= room[q]]
        if not full:
            break
        for q in full:
            out[q] = room[q]
            left -= room[q]
            open_.discard(q)
    if left > 0 and open_:
        for q in open_:
            out[q] = int(share[q])
        rest = left - sum(out[q] for q in open_)
        for q in sorted(open_, key=lambda q: (-(share[q] - int(share[q])), q))[:rest]:
            out[q] += 1
    return out


def inclusion_scale(bins: list[tuple[int, float]], k: int) -> float:
    """c with sum of n min(1, c g) = k, by bisection."""
    lo, hi = 0.0, 1.0
    def size(c: float) -> float:
        return sum(n * min(1.0, c * g) for n, g in bins)
    while size(hi) < k and hi < 1e18:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if size(mid) < k else (lo, mid)
    return hi


def prune_gaussian(ranked: DataFrame, k: int, id_col: str, spread: float = 0.20, sampler: str = "exact", seed: int = 42) -> DataFrame:
    return prune_shifted_gaussian(ranked, k, id_col, ShiftedGaussian(0.0, 0.5, spread), sampler, seed)


def selection_histogram(ranked: DataFrame, selected: DataFrame, id_col: str, bins: int = 20) -> DataFrame:
    """Per percentile bin: rows, selected rows, share."""
    q = F.least(F.floor(F.col("pct") * bins), F.lit(bins - 1)).cast("int").alias("bin")
    chosen = selected.select(F.col(id_col)).withColumn("_chosen", F.lit(1))
    return (
        ranked.join(chosen, id_col, "left").groupBy(q)
        .agg(F.count(F.lit(1)).alias("n"), F.count("_chosen").alias("kept"))
        .withColumn("share", F.col("kept") / F.col("n"))
    )


def sweep_pruning(ranked: DataFrame, grid: DataFrame, k: int, id_col: str, seed: int = 42, bins: int = 64) -> DataFrame:
    """(config, id) for each (config, discard, mean, spread) of a small grid; k samples each.

    Every config's cut is found from a histogram of its keys, so no config's rows are sorted
    as a whole.
    """
    out = None
    for r in grid.collect():
        cfg = ShiftedGaussian(r["discard"], r["mean"], r["spread"])
        own = prune_shifted_gaussian(ranked, k, id_col, cfg, "exact", seed).select(F.lit(r["config"]).alias("config"), id_col)
        out = own if out is None else out.unionByName(own)
    return out
