"""Rater networks: an instance MLP and, if wanted, a group MLP; frozen ones are stored as one row."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession

from gradsift.functions import networks
from gradsift.functions.udfs import mlp_score

#: A small fixed network over six statistics: hidden weights, hidden biases, output weights and bias.
FIXED_MLP = (
    np.array([[0.4, -0.8, 0.6, -0.5, -0.2, -0.1], [-0.3, 0.5, 0.7, 0.2, -0.4, 0.1], [0.2, -0.6, -0.4, 0.3, 0.1, 0.5]]),
    np.array([0.1, -0.2, 0.05]),
    np.array([1.0, 0.6, -0.4]),
    0.1,
)


@dataclass(frozen=True)
class RaterConfig:
    inputs: int = 6
    hidden: int = 16
    group: bool = True
    seed: int = 0


@dataclass(frozen=True)
class Rater:
    """Parameters. Output layers start at zero, so every sample starts with the same rating."""

    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    g1: np.ndarray
    gb1: np.ndarray
    g2: np.ndarray
    gb2: float
    group: bool = True

    @staticmethod
    def start(cfg: RaterConfig) -> Rater:
        rng = np.random.default_rng(cfg.seed)
        d, h = cfg.inputs, cfg.hidden
        return Rater(
            rng.normal(0, 1 / np.sqrt(d), (h, d)), np.zeros(h), np.zeros(h), 0.0,
            rng.normal(0, 1 / np.sqrt(2 * d), (h, 2 * d)), np.zeros(h), np.zeros(h), 0.0, cfg.group,
        )

    def raw(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(x @ self.w1.T + self.b1) @ self.w2 + self.b2

    def batch_weight(self, x: np.ndarray) -> float:
        if not self.group:
            return 1.0
        c = np.concatenate([x.mean(axis=0), x.var(axis=0)])
        return float(1 / (1 + np.exp(-(np.tanh(self.g1 @ c + self.gb1) @ self.g2 + self.gb2))))

    def weights(self, x: np.ndarray) -> tuple[np.ndarray, float]:
        s = self.raw(x)
        e = np.exp(s - s.max())
        return e / e.sum(), self.batch_weight(x)

    def gradient(self, x: np.ndarray, mult: np.ndarray) -> dict[str, np.ndarray | float]:
        """Of the sum of mult times weight, for each parameter."""
        a, b = self.weights(x)
        mean = float(a @ mult)
        ds = b * a * (mult - mean)
        hidden = np.tanh(x @ self.w1.T + self.b1)
        dh = ds[:, None] * self.w2 * (1 - hidden**2)
        out = {"w2": ds @ hidden, "b2": float(ds.sum()), "w1": dh.T @ x, "b1": dh.sum(axis=0)}
        if self.group:
            c = np.concatenate([x.mean(axis=0), x.var(axis=0)])
            h = np.tanh(self.g1 @ c + self.gb1)
            dz = mean * b * (1 - b)
            dg = dz * self.g2 * (1 - h**2)
            out |= {"g2": dz * h, "gb2": dz, "g1": np.outer(dg, c), "gb1": dg}
        return out

    def step(self, gradient: dict, rate: float) -> Rater:
        return replace(self, **{k: getattr(self, k) - rate * g for k, g in gradient.items()})

    def column(self, features: Column) -> Column:
        """The instance logit."""
        return _network(features, self.w1, self.b1, self.w2, self.b2)

    def batch_column(self, descriptor: Column) -> Column:
        """The batch logit of a descriptor."""
        return _network(descriptor, self.g1, self.gb1, self.g2, self.gb2)

    def row(self, spark: SparkSession, version: str) -> DataFrame:
        flat = {k: np.ravel(getattr(self, k)).tolist() for k in ("w1", "b1", "w2", "b2", "g1", "gb1", "g2", "gb2")}
        schema = "version string, hidden int, group boolean, " + ", ".join(f"{k} array<double>" for k in flat)
        return spark.createDataFrame([(version, len(self.b1), self.group, *flat.values())], schema)

    @staticmethod
    def read(row: DataFrame) -> Rater:
        r = row.first()
        h = r["hidden"]
        arrays = {k: np.array(r[k]) for k in ("w1", "b1", "w2", "g1", "gb1", "g2")}
        return Rater(arrays["w1"].reshape(h, -1), arrays["b1"], arrays["w2"], r["b2"][0], arrays["g1"].reshape(h, -1), arrays["gb1"], arrays["g2"], r["gb2"][0], r["group"])


def _network(x: Column, w1: np.ndarray, b1: np.ndarray, w2: np.ndarray, b2: float) -> Column:
    """An expression of a small network, else a vectorised function."""
    return networks.mlp(x, w1, b1, w2, b2) if w1.size <= networks.MAX_LITERALS else mlp_score(w1, b1, w2, b2)(x)


def average(raters: list[tuple[int, Rater]]) -> Rater:
    """Parameters' mean, weighted by sample counts."""
    total = sum(n for n, _ in raters)
    names = ("w1", "b1", "w2", "b2", "g1", "gb1", "g2", "gb2")
    return replace(raters[0][1], **{k: sum(n * getattr(r, k) for n, r in raters) / total for k in names})


