"""The experiments: selections by method at equal sizes, held against the same evaluation set.

run(name, spark, sf_dir, seed, **overrides) returns rows (method, k, metric, value, visits).
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.functions import heuristics
from gradsift.functions.features import pool_text
from gradsift.functions.hashing import hash_uniform
from gradsift.operators import measures, pruning
from gradsift.operators.pruning import ShiftedGaussian
from gradsift.operators.ranking import rank_corpus
from gradsift.plans.downstream import class_shares, train_methods, train_softmax
from gradsift.plans.rater import RaterConfig
from gradsift.plans.training import MetaConfig, MetaTrainer, TrainState, rate_in_batches, shards_for
from gradsift.sources import corpora
from gradsift.sources.staging import staged

SHIFTED = ShiftedGaussian()
_TRAINED: dict[tuple, TrainState] = {}


def train_rater(spark: SparkSession, sf_dir: str, cfg: MetaConfig = MetaConfig(), shards: int = 0, rounds: int = 5) -> TrainState:
    """Trained on all rows, once for a table and a configuration, and used by every experiment after."""
    key = (sf_dir, repr(cfg), shards, rounds)
    if key not in _TRAINED:
        pool, val = pool_text(corpora.train_pool(spark, sf_dir)), corpora.wanted(spark, sf_dir)
        _TRAINED[key] = MetaTrainer(cfg, shards, rounds).run(pool, val)[0]
    return _TRAINED[key]


def rater_visits(n: int, cfg: MetaConfig = MetaConfig()) -> int:
    """Training rows that all shards' steps visit."""
    return shards_for(cfg, n) * cfg.steps * cfg.batch


def ranked_pool(spark: SparkSession, sf_dir: str, cfg: MetaConfig = MetaConfig()) -> DataFrame:
    """The training pool, ranked by a trained rater: doc_id, score, rank, pct."""
    return rated_ranks(corpora.train_pool(spark, sf_dir), train_rater(spark, sf_dir, cfg))


def rated_ranks(pool: DataFrame, state: TrainState) -> DataFrame:
    """Texts are read once, for the ratings; what is ranked are ids and scores."""
    ratings = staged(rate_in_batches(pool_text(pool.select("doc_id", "text")), state.rater))
    return staged(rank_corpus(ratings, "score", "doc_id"), "ranks")


def schemes(ranked: DataFrame, k: int, ratio: float, seed: int = 42, blocks: bool = True) -> dict[str, DataFrame]:
    """The five pruning schemes at the same size."""
    out = {
        "random": pruning.prune_random(ranked, k, "doc_id", seed),
        "top_k": pruning.prune_top_k(ranked, k),
        "centred": pruning.prune_gaussian(ranked, k, "doc_id", seed=seed),
        "shifted": pruning.prune_shifted_gaussian(ranked, k, "doc_id", SHIFTED, seed=seed),
    }
    if blocks:
        out |= {f"block_s{s}": pruning.prune_block(ranked, s / 100, ratio) for s in range(0, 81, 20)}
    return out


def stacked(selections: dict[str, DataFrame], columns: list[str]) -> DataFrame:
    out = None
    for name, df in selections.items():
        own = df.select(F.lit(name).alias("method"), *columns)
        out = own if out is None else out.unionByName(own)
    return out


def trained_on(selections: dict[str, DataFrame], pool: DataFrame, val: DataFrame, **how) -> DataFrame:
    """Curves of models trained on every document of each selection. Only ids are stacked."""
    return train_methods(staged(stacked(selections, ["doc_id"]), "selections"), pool, val, **how)


def as_results(curve: DataFrame, metric: str = "val_loss") -> DataFrame:
    """The last epoch's value of each method."""
    last = curve.groupBy("method").agg(F.max_by(F.struct("k", "visits", "val_loss"), "epoch").alias("x"))
    return last.select("method", F.col("x.k").alias("k"), F.lit(metric).alias("metric"), F.col("x.val_loss").alias("value"), F.col("x.visits").alias("visits"))


def text_moments(selections: dict[str, DataFrame], pool: DataFrame, reference: DataFrame) -> DataFrame:
    """Diagonal Frechet distance of each selection's text statistics from the reference's."""
    f = F.col("features")
    agg = [F.avg(f[i]).alias(f"m{i}") for i in range(6)] + [F.stddev_pop(f[i]).alias(f"s{i}") for i in range(6)]
    shapes = staged(pool_text(pool).select("doc_id", "features"), "features")
    own = stacked(selections, ["doc_id"]).join(shapes, "doc_id").groupBy("method").agg(F.count(F.lit(1)).alias("k"), *agg)
    ref = pool_text(reference).agg(*agg).withColumnsRenamed({f"{c}{i}": f"r{c}{i}" for c in "ms" for i in range(6)})
    total = F.lit(0.0)
    for i in range(6):
        for c in "ms":
            total = total + (F.col(f"{c}{i}") - F.col(f"r{c}{i}")) * (F.col(f"{c}{i}") - F.col(f"r{c}{i}"))
    return own.crossJoin(F.broadcast(ref)).select("method", "k", F.lit("frechet_diag").alias("metric"), total.alias("value"), F.lit(0).cast("long").alias("visits"))


def random_and_shifted(ranked: DataFrame, k: int, seed: int, suffix: str = "") -> dict[str, DataFrame]:
    return {
        f"random{suffix}": pruning.prune_random(ranked, k, "doc_id", seed),
        f"shifted{suffix}": pruning.prune_shifted_gaussian(ranked, k, "doc_id", SHIFTED, seed=seed),
    }


def heuristic_ranks(corpus: DataFrame) -> dict[str, DataFrame]:
    """The corpus (doc_id, text, features) ranked by each of the four heuristics."""
    f = F.col("features")
    scores = staged(corpus.select(
        "doc_id", heuristics.aesthetic(f).alias("aesthetic"), heuristics.text_clarity(F.col("text")).alias("clarity"), heuristics.text_edges(F.col("text")).alias("edges"),
    ))
    # a document without words has no rare one
    rare = staged(scores.select("doc_id").join(heuristics.rare_word_share(corpus), "doc_id", "left").select("doc_id", F.coalesce("rare_share", F.lit(0.0)).alias("frequency")))
    sources = {"aesthetic": scores, "clarity": scores, "frequency": rare, "edges": scores}
    return {name: staged(rank_corpus(df.select("doc_id", F.col(name).alias("score")), "score", "doc_id"), "ranks") for name, df in sources.items()}


def three_ways(ranked: DataFrame) -> dict[str, DataFrame]:
    """Half of a ranking: its top, its middle, and what is left between trimmed ends."""
    return {"top": pruning.prune_block(ranked, 0.0, 0.5), "middle": pruning.prune_block(ranked, 0.25, 0.5), "trimmed": pruning.prune_trimmed(ranked, 0.5)}


def comparison(spark: SparkSession, sf_dir: str, seed: int = 42, epochs: int = 3) -> DataFrame:
    """Full, random, the four heuristics at half, each by the pruning that is best for it, and the method at a fifth and a half."""
    pool, val, ranked = corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir), ranked_pool(spark, sf_dir)
    n = ranked.count()
    sets = {"full": ranked, "random": pruning.prune_random(ranked, n // 2, "doc_id", seed)}
    for name, r in heuristic_ranks(pool_text(pool)).items():
        # at half, the middle and the trimmed are the same rows
        sets |= {f"{name}_{way}": kept for way, kept in three_ways(r).items() if way != "trimmed"}
    for share in (20, 50):
        sets[f"shifted_{share}"] = pruning.prune_shifted_gaussian(ranked, n * share // 100, "doc_id", SHIFTED, seed=seed)
    results = as_results(trained_on(sets, pool, val, epochs=epochs))
    losses = {r["method"]: r["value"] for r in results.collect()}
    kept = set(sets)
    for name in ("aesthetic", "clarity", "frequency", "edges"):
        ways = [m for m in sets if m.startswith(f"{name}_")]
        kept -= set(ways) - {min(ways, key=lambda m: (losses.get(m, float("inf")), m))}
    return results.where(F.col("method").isin(sorted(kept))).unionByName(text_moments({m: df for m, df in sets.items() if m in kept}, pool, val))


def pruning_comparison(spark: SparkSession, sf_dir: str, seed: int = 42, ratio: float = 0.2, epochs: int = 3) -> DataFrame:
    ranked = ranked_pool(spark, sf_dir)
    sets = schemes(ranked, int(ranked.count() * ratio), ratio, seed)
    return as_results(trained_on(sets, corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir), epochs=epochs))


def model_scale(spark: SparkSession, sf_dir: str, seed: int = 42, epochs: int = 3) -> DataFrame:
    """One selection for three sizes of the downstream model."""
    ranked, out = ranked_pool(spark, sf_dir), None
    sets = random_and_shifted(ranked, ranked.count() // 5, seed)
    for vocab in (8, 32, 128):
        curve = trained_on(sets, corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir), vocab=vocab, epochs=epochs)
        own = as_results(curve, f"val_loss_v{vocab}")
        out = own if out is None else out.unionByName(own)
    return out


def data_scale(spark: SparkSession, sf_dir: str, seed: int = 42, epochs: int = 3) -> DataFrame:
    return _shares(ranked_pool(spark, sf_dir), corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir), (10, 20, 50), seed, epochs)


def _shares(ranked: DataFrame, pool: DataFrame, val: DataFrame, shares: tuple[int, ...], seed: int, epochs: int = 3) -> DataFrame:
    n, sets = ranked.count(), {}
    for share in shares:
        sets |= random_and_shifted(ranked, n * share // 100, seed, f"_{share}")
    return as_results(trained_on(sets, pool, val, epochs=epochs))


def cross_family(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Ratings from one family for others: a low-rank adapter, one epoch, and a softmax model of the language."""
    ranked, pool, val = ranked_pool(spark, sf_dir), corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir)
    sets = random_and_shifted(ranked, ranked.count() // 5, seed)
    base = train_rater(spark, sf_dir).theta_hat * 0.5
    adapter = as_results(trained_on(sets, pool, val, epochs=1, rank=4, rate=0.5, base=base), "adapter_val_loss")
    langs = corpora.table(spark, sf_dir, "documents").select("doc_id", "lang")
    known = [r["lang"] for r in langs.where("lang IS NOT NULL").select("lang").distinct().orderBy("lang").collect()]

    def shares(docs: DataFrame) -> DataFrame:
        return class_shares(docs.select("doc_id", "text").join(langs, "doc_id"), "doc_id", "text", "lang")

    softmax = train_softmax(staged(stacked(sets, ["doc_id"]), "selections"), shares(pool), shares(val), known)
    return adapter.unionByName(as_results(softmax, "softmax_val_loss"))


def mixed_domain(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Preferred and non-preferred documents mixed."""
    items = corpora.preference_pairs(spark, sf_dir).select(F.col("item_id").alias("doc_id"))
    docs = corpora.table(spark, sf_dir, "documents").select("doc_id", "text")
    val = corpora.wanted(spark, sf_dir)
    pool = docs.join(items, "doc_id", "left_semi").join(val.select("doc_id"), "doc_id", "left_anti")
    return _shares(rated_ranks(pool, train_rater(spark, sf_dir)), pool, val, (20, 50), seed)


def second_domain(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Conversation turns; a hash tenth is held out."""
    turns = corpora.dialogue_corpus(spark, sf_dir).select("doc_id", "text")
    held = hash_uniform("doc_id", 9) < 0.1
    return _shares(rated_ranks(turns.where(~held), train_rater(spark, sf_dir)), turns.where(~held), turns.where(held), (20, 50), seed)


def ablation(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Top-K, centred and shifted without the group part, and shifted with it."""
    alone = ranked_pool(spark, sf_dir, MetaConfig(rater=RaterConfig(group=False)))
    both = ranked_pool(spark, sf_dir)
    k = alone.count() // 5
    sets = {
        "top_k": pruning.prune_top_k(alone, k), "centred": pruning.prune_gaussian(alone, k, "doc_id", seed=seed),
        "shifted": pruning.prune_shifted_gaussian(alone, k, "doc_id", SHIFTED, seed=seed), "shifted_group": pruning.prune_shifted_gaussian(both, k, "doc_id", SHIFTED, seed=seed),
    }
    return as_results(trained_on(sets, corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir)))


def training_trend(spark: SparkSession, sf_dir: str, seed: int = 42, epochs: int = 10) -> DataFrame:
    """Validation loss by epoch: method, k, epoch, visits, val_loss."""
    ranked = ranked_pool(spark, sf_dir)
    n = ranked.count()
    sets = {
        "random_50": pruning.prune_random(ranked, n // 2, "doc_id", seed), "shifted_20": pruning.prune_shifted_gaussian(ranked, n // 5, "doc_id", SHIFTED, seed=seed),
        "shifted_50": pruning.prune_shifted_gaussian(ranked, n // 2, "doc_id", SHIFTED, seed=seed),
    }
    return trained_on(sets, corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir), epochs=epochs, rate=2.0)


def _timed(curve: DataFrame) -> DataFrame:
    """Visits are the time: equal batches cost the same in every method."""
    return staged(curve, "curves").select("method", "epoch", F.col("visits").cast("double").alias("elapsed"), F.col("val_loss").alias("value"))


def speedup(spark: SparkSession, sf_dir: str, seed: int = 42, epochs: int = 10) -> DataFrame:
    """Visits in which each selection reaches the best loss that a random half reaches, against the half's own."""
    return measures.time_to_target(_timed(training_trend(spark, sf_dir, seed, epochs)), "random_50")


def stability(spark: SparkSession, sf_dir: str, seed: int = 42, epochs: int = 10) -> DataFrame:
    """Changes of direction of the trained curves, and their largest rise."""
    return measures.curve_stability(_timed(training_trend(spark, sf_dir, seed, epochs)))


def one_stage(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """The head of ratings learned by the loss rule, without the second stage; with it; and random."""
    ranked = ranked_pool(spark, sf_dir, MetaConfig(rule="loss"))
    k = ranked.count() // 5
    sets = random_and_shifted(ranked, k, seed) | {"one_stage": pruning.prune_top_k(ranked, k)}
    return as_results(trained_on(sets, corpora.train_pool(spark, sf_dir), corpora.wanted(spark, sf_dir)))


def update_rules(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Gap and loss rules, with and without the group part: AUC against quality, last batch weight."""
    labels, out = corpora.table(spark, sf_dir, "labels").select("doc_id", "quality"), None
    visits = rater_visits(corpora.train_pool(spark, sf_dir).select("doc_id").count())
    for rule in ("gap", "loss"):
        for group in (True, False):
            cfg = MetaConfig(rule=rule, rater=RaterConfig(group=group))
            pool = rate_in_batches(pool_text(corpora.train_pool(spark, sf_dir)), train_rater(spark, sf_dir, cfg).rater)
            own = measures.auc(pool.join(labels, "doc_id"), "score", "quality")
            row = own.select(F.lit(f"{rule}_{'group' if group else 'alone'}").alias("method"), (F.col("positives") + F.col("negatives")).alias("k"), F.lit("auc").alias("metric"), F.col("auc").alias("value"), F.lit(visits).cast("long").alias("visits"))
            out = row if out is None else out.unionByName(row)
    return out


def amortisation(spark: SparkSession, sf_dir: str, seed: int = 42) -> DataFrame:
    """Visits and seconds of the rater's training, run anew, against those of the data-scale runs that use it."""
    pool = corpora.train_pool(spark, sf_dir)
    began = time.monotonic()
    state, log = MetaTrainer(MetaConfig(), 0, 5).run(pool_text(pool), corpora.wanted(spark, sf_dir))
    rater_s, began = time.monotonic() - began, time.monotonic()
    runs = _shares(rated_ranks(pool, state), pool, corpora.wanted(spark, sf_dir), (10, 20, 50), seed)
    down, down_s = sum(r["visits"] for r in runs.collect()), time.monotonic() - began
    visits = len(log) * MetaConfig.batch * 2
    return spark.createDataFrame([(visits, rater_s, down, down_s, visits / down)], "rater_visits long, rater_seconds double, downstream_visits long, downstream_seconds double, share double")


EXPERIMENTS: dict[str, Callable[..., DataFrame]] = {
    "method_comparison": comparison, "pruning_comparison": pruning_comparison, "model_scale": model_scale, "data_scale": data_scale,
    "cross_family": cross_family, "mixed_domain": mixed_domain, "second_domain": second_domain, "ablation": ablation,
    "training_trend": training_trend, "speedup": speedup, "stability": stability, "one_stage": one_stage, "update_rules": update_rules, "amortisation": amortisation,
}


def run(name: str, spark: SparkSession, sf_dir: str, **overrides) -> DataFrame:
    return EXPERIMENTS[name](spark, sf_dir, **overrides)
