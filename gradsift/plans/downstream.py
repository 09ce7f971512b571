"""Downstream models trained on selections, and fitted estimators."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradsift.functions.hashing import hash32
from gradsift.sources.staging import staged


def fit_estimator(labelled: DataFrame, features: str, label: str, steps: int = 12, ridge: float = 1e-3) -> tuple[list[float], float]:
    """Logistic regression by Newton steps; each is one aggregation of d x d numbers."""
    d = len(labelled.select(features).first()[0])
    x = [*(F.col(features)[i] for i in range(d)), F.lit(1.0)]
    theta = np.zeros(d + 1)
    rows = labelled.select(features, label).cache()
    for _ in range(steps):
        z = F.lit(0.0)
        for xi, t in zip(x, theta, strict=True):
            z = z + xi * F.lit(float(t))
        p = F.lit(1.0) / (F.lit(1.0) + F.exp(-z))
        r = p - F.col(label)
        aggs = [F.sum(r * xi).alias(f"g{i}") for i, xi in enumerate(x)]
        aggs += [F.sum(p * (1 - p) * x[i] * x[j]).alias(f"h{i}_{j}") for i in range(d + 1) for j in range(i + 1)]
        row = rows.agg(*aggs).first()
        g = np.array([row[f"g{i}"] for i in range(d + 1)]) + ridge * theta
        h = np.array([[row[f"h{max(i, j)}_{min(i, j)}"] for j in range(d + 1)] for i in range(d + 1)]) + ridge * np.eye(d + 1)
        step = np.linalg.solve(h, g)
        theta = theta - step
        if np.abs(step).max() < 1e-8:
            break
    rows.unpersist()
    return theta[:d].tolist(), float(theta[d])


def bigram_nll(logits: np.ndarray) -> np.ndarray:
    top = logits.max(axis=1, keepdims=True)
    return np.log(np.exp(logits - top).sum(axis=1, keepdims=True)) + top - logits


class Profiles:
    """Sparse bigram counts of samples, scaled to shares; losses and gradients of all at once."""

    def __init__(self, cells: list[np.ndarray], counts: list[np.ndarray], vocab: int):
        self.vocab = vocab
        self.sizes = np.array([len(c) for c in cells], dtype=np.int64)
        self.at = np.concatenate([[0], np.cumsum(self.sizes)]).astype(np.int64)
        self.cells = np.concatenate([np.zeros(0, dtype=np.int64), *cells]).astype(np.int64)
        self.shares = np.concatenate([np.zeros(0), *(np.asarray(n, dtype=float) / max(1, np.sum(n)) for n in counts)])
        self.owner = np.repeat(np.arange(len(cells)), self.sizes)

    def __len__(self) -> int:
        return len(self.sizes)

    def take(self, rows: np.ndarray) -> Profiles:
        out = Profiles([], [], self.vocab)
        out.sizes = self.sizes[rows]
        out.at = np.concatenate([[0], np.cumsum(out.sizes)])
        pick = np.repeat(self.at[rows] - out.at[:-1], out.sizes) + np.arange(out.at[-1])
        out.cells, out.shares, out.owner = self.cells[pick], self.shares[pick], np.repeat(np.arange(len(rows)), out.sizes)
        return out

    def losses(self, logits: np.ndarray) -> np.ndarray:
        """Mean negative log-likelihood; 0 for a sample without a transition."""
        return np.bincount(self.owner, self.shares * bigram_nll(logits).ravel()[self.cells], minlength=len(self))

    def gradient(self, logits: np.ndarray, weights: np.ndarray) -> np.ndarray:
        """The weighted sum of the samples' gradients."""
        c = np.bincount(self.cells, self.shares * weights[self.owner], minlength=self.vocab**2).reshape(self.vocab, self.vocab)
        return c.sum(axis=1, keepdims=True) * np.exp(-bigram_nll(logits)) - c

    def norms(self, logits: np.ndarray) -> np.ndarray:
        """Euclidean norm of each sample's gradient, from row sums and without forming it."""
        p = np.exp(-bigram_nll(logits))
        row = self.cells // self.vocab
        rows = np.bincount(self.owner * self.vocab + row, self.shares, minlength=len(self) * self.vocab).reshape(len(self), self.vocab)
        cross = np.bincount(self.owner, rows.ravel()[self.owner * self.vocab + row] * p.ravel()[self.cells] * self.shares, minlength=len(self))
        own = np.bincount(self.owner, self.shares**2, minlength=len(self))
        return np.sqrt(np.maximum(rows**2 @ (p**2).sum(axis=1) - 2 * cross + own, 0))


def with_profiles(df: DataFrame, id_col: str, text_col: str, vocab: int, keep: list[str]) -> DataFrame:
    """(id, kept columns, cells, counts)."""
    from gradsift.functions.features import bigram_profile

    kinds = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in [id_col, *keep])

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            made = [bigram_profile(t, vocab) for t in f[text_col]]
            out = f[[id_col, *keep]].copy()
            out["cells"] = [c for c, _ in made]
            out["counts"] = [n for _, n in made]
            yield out

    return df.select(id_col, *keep, text_col).mapInPandas(run, f"{kinds}cells array<long>, counts array<long>")


def traces(df: DataFrame, models: list[np.ndarray], vocab: int) -> DataFrame:
    """(doc_id, epoch, loss, grad_norm) of every text under each epoch's model: map-only."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            p = Profiles(list(f["cells"]), list(f["counts"]), vocab)
            for epoch, logits in enumerate(models):
                yield pd.DataFrame({"doc_id": f["doc_id"], "epoch": epoch, "loss": p.losses(logits), "grad_norm": p.norms(logits)})

    kind = df.schema["doc_id"].dataType.simpleString()
    return with_profiles(df, "doc_id", "text", vocab, []).mapInPandas(run, f"doc_id {kind}, epoch int, loss double, grad_norm double")


def train_bigram(p: Profiles, epochs: int, batch: int, rate: float, seed: int, val: Profiles | None = None, start: np.ndarray | None = None) -> tuple[np.ndarray, list[tuple[int, float]]]:
    """Minibatch descent from uniform logits; the validation loss after each epoch."""
    logits = np.zeros((p.vocab, p.vocab)) if start is None else start.copy()
    rng, curve = np.random.default_rng(seed), []
    for epoch in range(1, epochs + 1):
        order = rng.permutation(len(p))
        for at in range(0, len(order), batch):
            own = p.take(order[at : at + batch])
            logits -= rate * own.gradient(logits, np.full(len(own), 1 / len(own)))
        curve.append((epoch, float(val.losses(logits).mean()) if val is not None else float("nan")))
    return logits, curve


#: Rows of the largest selection that one task trains on.
SHARD_ROWS = 10_000


def mean_profile(df: DataFrame, text_col: str, vocab: int) -> np.ndarray:
    """Mean bigram shares of all texts. A model's mean loss over the texts is linear in them."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from gradsift.functions.features import bigram_profile

        n, total = 0, np.zeros(vocab**2)
        for f in frames:
            for t in f[text_col]:
                cells, counts = bigram_profile(t, vocab)
                total[cells] += counts / max(1, counts.sum())
            n += len(f)
        yield pd.DataFrame({"n": [n], "total": [total.tobytes()]})

    n, total = 0, np.zeros(vocab**2)
    for r in df.select(text_col).mapInPandas(run, "n long, total binary").collect():
        n, total = n + r["n"], total + np.frombuffer(r["total"])
    return total / max(1, n)


def train_epochs(selections: DataFrame, pool: DataFrame, vocab: int, epochs: int, batch: int, rate: float, seed: int, rank: int = 0, base: np.ndarray | None = None, shard_rows: int = SHARD_ROWS) -> Iterator[tuple[int, dict[str, tuple[int, np.ndarray]]]]:
    """After each epoch over every row of each selection: (epoch, {method: (rows, logits)}).

    A method's rows are split over shards by hash; each descends from the epoch's common
    start and the parameters are averaged, weighted by rows. All methods have the number of
    shards that the largest needs, so a method's steps stay in proportion to its rows; with
    one shard it is plain sequential descent.
    """
    spark = selections.sparkSession
    texts = pool.select("doc_id", "text").join(selections.select("doc_id"), "doc_id", "left_semi")
    profiles = staged(with_profiles(texts, "doc_id", "text", vocab, []), "profiles")
    sizes = {r["method"]: r["count"] for r in selections.groupBy("method").count().collect()}
    shards = max(1, -(-max(sizes.values(), default=0) // shard_rows))
    rows = profiles.join(selections.select("method", "doc_id"), "doc_id").withColumn("shard", (hash32("doc_id", seed + 1) % shards).cast("int"))
    rows = rows.repartition("method", "shard").persist(StorageLevel.MEMORY_AND_DISK)
    frozen = np.zeros((vocab, vocab)) if base is None else base
    first = (np.random.default_rng(seed).normal(0, 0.3, (vocab, rank)), np.zeros((rank, vocab))) if rank else (frozen,)
    states = dict.fromkeys(sizes, first)

    def run_epoch(epoch: int, sent):
        def run(f: pd.DataFrame) -> pd.DataFrame:
            method, shard = f["method"].iloc[0], int(f["shard"].iloc[0])
            f = f.sort_values("doc_id")
            p, now = Profiles(list(f["cells"]), list(f["counts"]), vocab), sent.value[method]
            own = seed + 1000 * epoch + shard
            now = adapter_epoch(p, frozen, *now, batch, rate, own) if rank else (train_bigram(p, 1, batch, rate, own, start=now[0])[0],)
            return pd.DataFrame({"method": [method], "n": [len(p)], "state": [pickle.dumps(now)]})

        return run

    try:
        for epoch in range(1, epochs + 1):
            sent = spark.sparkContext.broadcast(states)
            done = staged(rows.groupBy("method", "shard").applyInPandas(run_epoch(epoch, sent), "method string, n long, state binary"), "epochs")
            seen, sums = dict.fromkeys(sizes, 0), {m: [np.zeros_like(x) for x in first] for m in sizes}
            for r in done.toLocalIterator():
                seen[r["method"]] += r["n"]
                for total, x in zip(sums[r["method"]], pickle.loads(r["state"]), strict=True):
                    total += r["n"] * x
            states = {m: tuple(x / seen[m] for x in sums[m]) for m in sizes}
            sent.unpersist()
            yield epoch, {m: (seen[m], frozen + s[0] @ s[1] if rank else s[0]) for m, s in states.items()}
    finally:
        rows.unpersist()


def train_methods(selections: DataFrame, pool: DataFrame, val: DataFrame, vocab: int = 32, epochs: int = 3, batch: int = 64, rate: float = 8.0, seed: int = 42, rank: int = 0, base: np.ndarray | None = None, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(method, k, epoch, visits, val_loss): one model a method, with equal epochs over all its rows and equal batches.

    selections: method, doc_id; pool: doc_id, text. rank > 0 trains a low-rank addition to
    frozen base logits in place of all logits.
    """
    held, curve = mean_profile(val, "text", vocab), []
    for epoch, models in train_epochs(selections, pool, vocab, epochs, batch, rate, seed, rank, base, shard_rows):
        curve += [(m, k, epoch, k * epoch, float(held @ bigram_nll(logits).ravel())) for m, (k, logits) in sorted(models.items())]
    return selections.sparkSession.createDataFrame(curve, "method string, k long, epoch int, visits long, val_loss double")


def adapter_epoch(p: Profiles, base: np.ndarray, a: np.ndarray, b: np.ndarray, batch: int, rate: float, seed: int | np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """One pass over the rows; both factors step from the values before."""
    order = np.random.default_rng(seed).permutation(len(p))
    for at in range(0, len(order), batch):
        own = p.take(order[at : at + batch])
        g = own.gradient(base + a @ b, np.full(len(own), 1 / len(own)))
        a, b = a - rate * g @ b.T, b - rate * a.T @ g
    return a, b


def train_adapter(p: Profiles, val: Profiles, base: np.ndarray | None, rank: int, epochs: int, batch: int, rate: float, seed: int) -> list[tuple[int, float]]:
    """Frozen logits and a trained product of two thin matrices."""
    rng = np.random.default_rng(seed)
    base = np.zeros((p.vocab, p.vocab)) if base is None else base
    a, b = rng.normal(0, 0.3, (p.vocab, rank)), np.zeros((rank, p.vocab))
    curve = []
    for epoch in range(1, epochs + 1):
        a, b = adapter_epoch(p, base, a, b, batch, rate, rng)
        curve.append((epoch, float(val.losses(base + a @ b).mean())))
    return curve


def generate(logits: np.ndarray, n: int, length: int, seed: int = 42) -> np.ndarray:
    """n sequences of classes by ancestral sampling."""
    rng = np.random.default_rng(seed)
    cumulative = np.cumsum(np.exp(-bigram_nll(logits)), axis=1)
    out = np.zeros((n, length), dtype=np.int64)
    out[:, 0] = rng.integers(0, len(logits), n)
    for t in range(1, length):
        out[:, t] = np.minimum((cumulative[out[:, t - 1]] < rng.random(n)[:, None]).sum(axis=1), len(logits) - 1)
    return out


def class_shares(df: DataFrame, id_col: str, text_col: str, label_col: str, vocab: int = 32) -> DataFrame:
    """(id, label, x): roots of the shares of the text's character classes, inputs of the second model family."""
    from gradsift.functions.features import text_classes

    kind = df.schema[id_col].dataType.simpleString()

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            counts = [np.bincount(text_classes(t, vocab), minlength=vocab) for t in f["_text"]]
            yield pd.DataFrame({id_col: f[id_col], "label": f["label"], "x": [np.sqrt(c / max(1, c.sum())) for c in counts]})

    source = df.where(F.col(label_col).isNotNull()).select(id_col, F.col(label_col).alias("label"), F.col(text_col).alias("_text"))
    return source.mapInPandas(run, f"`{id_col}` {kind}, label string, x array<double>")


def train_softmax(selections: DataFrame, rows: DataFrame, val: DataFrame, labels: list[str], steps: int = 12, rate: float = 2.5) -> DataFrame:
    """(method, k, epoch, visits, val_loss) of a multinomial logistic model of the label, by full-batch descent.

    selections: method, doc_id; rows and val: doc_id, label, x. Every row is in every step; a
    task sends the sums of its part for each method, whose size is that of the model.
    """
    place, d = {x: i for i, x in enumerate(labels)}, len(rows.select("x").first()["x"]) + 1
    held = staged(val.select(F.lit("").alias("method"), "label", "x"), "held")
    joined = staged(rows.join(selections.select("method", "doc_id"), "doc_id").select("method", "label", "x").unionByName(held), "softmax")
    methods = [r["method"] for r in selections.select("method").distinct().orderBy("method").collect()]
    theta = {m: np.zeros((len(labels), d)) for m in methods}

    def sums(sent):
        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            total = {}
            for f in frames:
                for method, own in f.groupby("method"):
                    x = np.column_stack([np.stack(own["x"].to_numpy()), np.ones(len(own))])
                    y = own["label"].map(place).to_numpy(dtype=np.int64)
                    for m in sent.value if method == "" else [method]:
                        nll = bigram_nll(x @ sent.value[m].T)
                        slot = total.setdefault((method, m), [0, 0.0, np.zeros((len(place), d))])
                        slot[0] += len(own)
                        slot[1] += float(nll[np.arange(len(own)), y].sum())
                        if method:
                            p = np.exp(-nll)
                            p[np.arange(len(own)), y] -= 1
                            slot[2] += p.T @ x
            yield pd.DataFrame([(k[0], k[1], n, loss, g.tobytes()) for k, (n, loss, g) in total.items()], columns=["part", "method", "n", "loss", "g"])

        return run

    curve, spark = [], selections.sparkSession
    for step in range(steps + 1):
        sent = spark.sparkContext.broadcast(theta)
        got = joined.mapInPandas(sums(sent), "part string, method string, n long, loss double, g binary").collect()
        sent.unpersist()
        new = {}
        for m in methods:
            own = [r for r in got if r["method"] == m]
            n, n_val = (sum(r["n"] for r in own if (r["part"] == "") == v) for v in (False, True))
            curve.append((m, n, step, n * step, sum(r["loss"] for r in own if r["part"] == "") / max(1, n_val)))
            new[m] = theta[m] - rate * sum((np.frombuffer(r["g"]).reshape(len(labels), d) for r in own if r["part"]), np.zeros((len(labels), d))) / max(1, n)
        theta = new
    return spark.createDataFrame(curve, "method string, k long, epoch int, visits long, val_loss double")
