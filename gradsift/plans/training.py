"""The vectorised meta-gradient engine.

One NumPy kernel runs the unrolled scheme on every row: warm-up of the reference proxy on
training data, hand-over, then joint steps of the primary proxy (weighted training and
validation gradients), the reference (training only) and the rater. The rows are split over
shards, whose number grows with the corpus; they run in parallel for a round and their
parameters are averaged, weighted by samples. One shard is plain sequential descent.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradsift.functions.hashing import hash32
from gradsift.functions.networks import sigmoid
from gradsift.operators.batching import assign_batches
from gradsift.operators.rating import batch_descriptor, rate
from gradsift.plans.downstream import Profiles, with_profiles
from gradsift.plans.rater import Rater, RaterConfig, average
from gradsift.sources.staging import staged


@dataclass(frozen=True)
class MetaConfig:
    rule: str = "gap"
    beta: float = 2.0
    alpha: float = 0.5
    decay: float = 0.0
    warmup_steps: int = 20
    steps: int = 300
    batch: int = 64
    vocab: int = 32
    reference_weighting: str = "rater"
    center_group: bool = False
    update: str = "batch"
    seed: int = 42
    rater: RaterConfig = field(default_factory=RaterConfig)

    def __post_init__(self) -> None:
        if self.rule not in ("gap", "loss") or self.update not in ("batch", "sample") or self.reference_weighting not in ("rater", "uniform"):
            raise ValueError("rule is gap or loss, update batch or sample, reference_weighting rater or uniform")

    def rate(self, base: float, k: int) -> float:
        return base / (1 + self.decay * k)


@dataclass(frozen=True)
class TrainState:
    theta: np.ndarray
    theta_hat: np.ndarray
    rater: Rater
    step: int = 0
    mean_mult: float = 0.0

    @staticmethod
    def start(cfg: MetaConfig) -> TrainState:
        zero = np.zeros((cfg.vocab, cfg.vocab))
        return TrainState(zero, zero, Rater.start(cfg.rater))


def warm_up(state: TrainState, batches, cfg: MetaConfig) -> TrainState:
    """Reference steps on training data alone; the primary then takes over its parameters."""
    theta = state.theta_hat
    for k, (p, _) in enumerate(batches):
        theta = theta - cfg.rate(cfg.beta, k) * p.gradient(theta, np.full(len(p), 1 / len(p)))
    return replace(state, theta=theta, theta_hat=theta)


def meta_step(state: TrainState, p: Profiles, x: np.ndarray, val: Profiles, cfg: MetaConfig) -> tuple[TrainState, dict]:
    """One joint step. All three updates use the parameters before it."""
    a, b = state.rater.weights(x)
    w = a * b
    beta, alpha = cfg.rate(cfg.beta, state.step), cfg.rate(cfg.alpha, state.step)
    primary = p.losses(state.theta)
    mult = primary - p.losses(state.theta_hat) if cfg.rule == "gap" else primary
    if cfg.update == "sample":
        one = np.zeros(len(p))
        chosen = state.step * 2654435761 % len(p)
        one[chosen] = mult[chosen]
        mult = one
    g_val = val.gradient(state.theta, np.full(len(val), 1 / len(val)))
    theta = state.theta - beta * (g_val + p.gradient(state.theta, w))
    reference = w if cfg.reference_weighting == "rater" else np.full(len(p), 1 / len(p))
    theta_hat = state.theta_hat if cfg.rule == "loss" else state.theta_hat - beta * p.gradient(state.theta_hat, reference)
    mean = float(a @ mult)
    grad = state.rater.gradient(x, mult)
    if cfg.center_group and cfg.rater.group and mean:
        share = (mean - state.mean_mult) / mean
        grad |= {k: grad[k] * share for k in ("g1", "gb1", "g2", "gb2")}
    rater = state.rater.step(grad, alpha)
    row = {"step": state.step, "batch_weight": b, "mean_mult": mean, "train_loss": float(primary.mean()), "val_loss": float(val.losses(state.theta).mean())}
    return TrainState(theta, theta_hat, rater, state.step + 1, 0.9 * state.mean_mult + 0.1 * mean), row


def _batches(p: Profiles, x: np.ndarray, size: int, n: int, seed: int, skip: int = 0):
    """n batches after the first skip ones; rows left over at the end of a pass come first in the next."""
    rng, order = np.random.default_rng(seed), np.zeros(0, dtype=int)
    size = min(size, len(p))
    for k in range(skip + n):
        if len(order) < size:
            order = np.concatenate([order, rng.permutation(len(p))])
        own, order = order[:size], order[size:]
        if k >= skip:
            yield p.take(own), x[own]


def run_steps(state: TrainState, p: Profiles, x: np.ndarray, val: Profiles, cfg: MetaConfig, steps: int, seed: int, skip: int = 0) -> tuple[TrainState, list[dict]]:
    log = []
    own = _batches(p, x, cfg.batch, steps, seed, skip)
    of_val = _batches(val, np.zeros((len(val), 1)), cfg.batch, steps, seed + 1, skip)
    for (b, f), (v, _) in zip(own, of_val, strict=True):
        state, row = meta_step(state, b, f, v, cfg)
        log.append(row)
    return state, log


def _shard_round(cfg: MetaConfig, id_col: str, sent, r: int, skip: int, steps: int):
    """The function that one shard runs in round r, going on where its last round's batches ended."""

    def train(f: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        if not len(f):
            return pd.DataFrame({"shard": pd.Series(dtype="int32"), "n": pd.Series(dtype="int64"), "state": pd.Series(dtype=object), "log": pd.Series(dtype=object)})
        f, held = f.sort_values(id_col), held.sort_values(id_col)
        p, x = Profiles(list(f["cells"]), list(f["counts"]), cfg.vocab), np.array(f["features"].tolist())
        v, now = Profiles(list(held["cells"]), list(held["counts"]), cfg.vocab), sent.value
        shard = int(f["shard"].iloc[0])
        seed = cfg.seed + 1000 * shard
        if r == 0:
            now = warm_up(now, _batches(p, x, cfg.batch, cfg.warmup_steps, seed), cfg)
        now, rows = run_steps(now, p, x, v, cfg, steps, seed, skip)
        return pd.DataFrame({"shard": [shard], "n": [len(p)], "state": [pickle.dumps(now)], "log": [pickle.dumps(rows)]})

    return train


def shards_for(cfg: MetaConfig, n: int) -> int:
    """As many as let a shard's steps visit each of its rows twice in the mean, so once for certain."""
    return max(1, -(-2 * n // (cfg.steps * cfg.batch)))


class MetaTrainer:
    """Trains a rater for a corpus and a validation set, on every row of both.

    corpus: id, text, features; val: id, text. shards: their number, 0 for shards_for. Each
    shard has a part of the validation set, of about a batch at least; parts are repeated
    where there are more shards.
    """

    def __init__(self, cfg: MetaConfig = MetaConfig(), shards: int = 1, rounds: int = 1):
        self.cfg, self.shards, self.rounds = cfg, shards, rounds

    def run(self, corpus: DataFrame, val: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[TrainState, pd.DataFrame]:
        cfg, spark = self.cfg, corpus.sparkSession
        rows = staged(with_profiles(corpus, id_col, text_col, cfg.vocab, ["features"]), "profiles")
        held = staged(with_profiles(val, id_col, text_col, cfg.vocab, []), "held")
        shards = self.shards or shards_for(cfg, rows.count())
        # twice a batch in the mean leaves no part empty
        parts = min(shards, max(1, held.count() // (2 * cfg.batch)))
        part = (hash32(id_col, cfg.seed + 2) % parts).cast("int")
        rows = rows.withColumn("shard", (hash32(id_col, cfg.seed + 1) % shards).cast("int")).repartition("shard").persist()
        held = held.withColumn("shard", F.explode(F.sequence(part, F.lit(shards - 1), F.lit(parts)))).repartition("shard").persist()
        state, log, done = TrainState.start(cfg), [], 0
        per_round = -(-cfg.steps // self.rounds)
        for r in range(self.rounds):
            sent = spark.sparkContext.broadcast(state)
            train = _shard_round(cfg, id_col, sent, r, done, per_round)
            both = rows.groupBy("shard").cogroup(held.groupBy("shard"))
            got = both.applyInPandas(train, "shard int, n long, state binary, log binary").toPandas().sort_values("shard")
            states = [(n, pickle.loads(s)) for n, s in zip(got["n"], got["state"], strict=True)]
            total = sum(n for n, _ in states)
            state = TrainState(
                sum(n * s.theta for n, s in states) / total, sum(n * s.theta_hat for n, s in states) / total,
                average([(n, s.rater) for n, s in states]), states[0][1].step, sum(n * s.mean_mult for n, s in states) / total,
            )
            log += [x | {"shard": i} for i, blob in zip(got["shard"], got["log"], strict=True) for x in pickle.loads(blob)]
            sent.unpersist()
            done += per_round
        rows.unpersist()
        held.unpersist()
        return state, pd.DataFrame(log)


def rate_corpus(corpus: DataFrame, rater: Rater, features: str = "features") -> DataFrame:
    """Adds score, the frozen rater's instance logit: map-only."""
    return corpus.withColumn("score", rater.column(F.col(features)))


def rate_in_batches(corpus: DataFrame, rater: Rater, id_col: str = "doc_id", features: str = "features", size: int = MetaConfig.batch) -> DataFrame:
    """(id, score): the instance logit and, with a group part, the log of the batch weight.

    Batches are fixed by hash and have the size of the training's in the mean; what meets in
    them are features, not texts.
    """
    rows = staged(corpus.select(id_col, features, rater.column(F.col(features)).alias("raw")), "logits")
    if not rater.group:
        return rate(rows, "raw").select(id_col, "score")
    rows = assign_batches(rows, id_col, size)
    weight = sigmoid(rater.batch_column(F.col("descriptor"))).alias("batch_weight")
    batches = batch_descriptor(rows, features, rater.w1.shape[1]).select("batch_id", weight)
    return rate(rows, "raw", "logit_group", batches).select(id_col, "score")
