"""Language identification by a mixture of languages, fitted for each document.

A model holds the probability of hashed byte trigrams in each language. A document's counts
are a mixture of the languages and of noise, whose trigrams are all alike; expectation
maximisation estimates the shares, and the set of languages is the one whose likelihood,
less a penalty for each member, is highest. The prediction is the largest share's language;
where noise alone is chosen, it is the likeliest language, with score 0.

Defined results: a text that is null or has no letter is ``und`` with score 0; so is any text
where the model has no language; equal shares, and texts without a trigram, go to the
language that sorts first; rows are independent of each other.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from gradsift.llm.bytescan import CHUNK_BYTES, chunks
from gradsift.llm.memory import trimmed

BINS = 1 << 15
_LATIN = re.compile("[A-Za-z]")


def has_letter(text: str) -> bool:
    """Whether a character of the general category L is in it: fractions and Roman numerals aren't."""
    return _LATIN.search(text) is not None or any(map(str.isalpha, text))


@lru_cache(maxsize=1)
def _folded() -> np.ndarray:
    """Letters in lower case and bytes of other scripts stay, all else is a space."""
    t = np.full(256, 32, dtype=np.uint64)
    t[97:123] = np.arange(97, 123)
    t[65:91] = np.arange(97, 123)
    t[128:] = np.arange(128, 256)
    return t


def _bins(data: np.ndarray) -> np.ndarray:
    """The bin of each trigram of the bytes; -1 for those with two spaces in a row."""
    if len(data) < 3:
        return np.zeros(0, dtype=np.int64)
    b = _folded()[data]
    code = (b[:-2] << np.uint64(16)) | (b[1:-1] << np.uint64(8)) | b[2:]
    hashed = (code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - 15)
    return np.where((b[:-2] == 32) & (b[1:-1] == 32) | (b[1:-1] == 32) & (b[2:] == 32), -1, hashed.astype(np.int64))


def _counted(pieces: Iterator[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    full = np.zeros(BINS, dtype=np.int64)
    for own in pieces:
        full += np.bincount(own[own >= 0], minlength=BINS)
    at = np.flatnonzero(full)
    return at, full[at]


def trigram_counts(texts: pa.Array, piece: int = CHUNK_BYTES) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(bins, counts) of each text. Trigrams of spaces alone don't count.

    A text longer than a piece is counted piece by piece, two bytes over each end, so that
    memory beside the text itself doesn't follow its length.
    """
    for c in chunks(texts, piece):
        if len(c) == 1:
            yield _counted(_bins(c.data[at : at + piece + 2]) for at in range(0, len(c.data), piece))
            continue
        bins = _bins(c.data)
        for d in range(len(c)):
            own = bins[c.offsets[d] : max(c.offsets[d], c.offsets[d + 1] - 2)]
            if len(own) > 4096:
                yield _counted(iter((own,)))
            else:
                yield np.unique(own[own >= 0], return_counts=True)


@dataclass(frozen=True)
class LanguageModel:
    """Rows of table: a language's trigram probabilities; the last row is noise."""

    languages: tuple[str, ...] = ()
    table: np.ndarray = field(default_factory=lambda: np.full((1, BINS), 1 / BINS))
    penalty: float = 6.0

    def shares(self, bins: np.ndarray, counts: np.ndarray, rounds: int = 12) -> tuple[np.ndarray, tuple[int, ...]]:
        """Each language's and the noise's share, and the chosen set."""
        m, n = len(self.languages) + 1, counts.sum()
        out = np.zeros(m)
        if not n:
            return out, ()
        like = self.table[:, bins].T
        pi = self._fit(like, counts, np.full(m, 1 / m), rounds)
        order = np.argsort(-pi, kind="stable")
        best, chosen = -np.inf, ()
        for k in range(1, m + 1):
            kept = order[:k]
            if k > 1 and pi[kept[-1]] < 0.02:
                break
            own = self._fit(like[:, kept], counts, np.full(k, 1 / k) if k > 1 else np.ones(1), rounds if k > 1 else 0)
            score = counts @ np.log(like[:, kept] @ own) - self.penalty * (k - 1) * np.log(n)
            if score > best:
                best, chosen = score, tuple(kept.tolist())
                out[:] = 0
                out[kept] = own
        return out, chosen

    def likeliest(self, bins: np.ndarray, counts: np.ndarray) -> int:
        """The language that alone explains the counts best."""
        return int((np.log(self.table[:-1, bins]) @ counts).argmax())

    @staticmethod
    def _fit(like: np.ndarray, counts: np.ndarray, pi: np.ndarray, rounds: int) -> np.ndarray:
        for _ in range(rounds):
            pi = pi * ((counts / (like @ pi)) @ like) / counts.sum()
        return pi


def fit(docs: DataFrame, lang_col: str = "lang", text_col: str = "text", id_col: str = "doc_id", max_docs: int = 20_000, smoothing: float = 0.5) -> LanguageModel:
    """A model of the labelled rows' languages, from a hash sample of max_docs rows in the mean.

    The driver gets a row for each language and trigram bin, whatever the number of documents.
    """
    labelled = docs.where(F.col(lang_col).isNotNull()).select(F.col(id_col).alias("_id"), F.col(lang_col).alias("_lang"), F.col(text_col).alias("_text"))
    n = labelled.count()
    if n > max_docs:
        labelled = labelled.where(F.pmod(F.xxhash64(F.lit("fit"), "_id"), F.lit(1 << 20)) < int(max_docs / n * (1 << 20)))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            langs = batch.column(0).to_pylist()
            for lang, (bins, counts) in zip(langs, trigram_counts(batch.column(1)), strict=True):
                total.setdefault(lang, np.zeros(BINS, dtype=np.int64))[bins] += counts
        for lang, own in total.items():
            at = np.flatnonzero(own)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at), pa.array(own[at])], names=["lang", "bin", "n"])

    rows = (
        labelled.select("_lang", "_text").mapInArrow(trimmed(count), "lang string, bin long, n long")
        .groupBy("lang", "bin").agg(F.sum("n").alias("n")).toPandas()
    )
    if not len(rows):
        return LanguageModel()
    languages = tuple(sorted(rows["lang"].unique()))
    table = np.full((len(languages) + 1, BINS), smoothing)
    table[[languages.index(x) for x in rows["lang"]], rows["bin"].to_numpy()] += rows["n"].to_numpy()
    table[-1] = 1
    return LanguageModel(languages, table / table.sum(axis=1, keepdims=True))


def identify(docs: DataFrame, model: LanguageModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The kept columns (all, if None), and _lang_pred, _score, _noise, _languages: the chosen set with shares."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    keep = docs.columns if keep is None else keep
    source = docs.select(*(F.col(f"`{c}`").alias(f"_k{i}") for i, c in enumerate(keep)), F.col(f"`{text_col}`").alias("_text"))
    schema = pa.schema(
        [(f"_k{i}", to_arrow_type(source.schema[f"_k{i}"].dataType)) for i in range(len(keep))]
        + [("_lang_pred", pa.string()), ("_score", pa.float64()), ("_noise", pa.float64()), ("_languages", pa.list_(pa.struct([("lang", pa.string()), ("share", pa.float64())])))]
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        names = m.languages
        for batch in batches:
            texts = batch.column(len(keep))
            pred, score, noise, sets = [], [], [], []
            for text, (bins, counts) in zip(texts, trigram_counts(texts), strict=True):
                raw = text.as_py()
                if raw is None or not names or not has_letter(raw):
                    pred.append("und")
                    score.append(0.0)
                    noise.append(0.0)
                    sets.append([])
                    continue
                shares, chosen = m.shares(bins, counts)
                k = int(shares[:-1].argmax()) if shares[:-1].any() else m.likeliest(bins, counts)
                pred.append(names[k])
                score.append(min(1.0, max(0.0, float(shares[k]))))
                noise.append(float(shares[-1]))
                sets.append([{"lang": names[j], "share": float(shares[j])} for j in chosen if j < len(names)])
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], *(pa.array(v, f.type) for v, f in zip((pred, score, noise, sets), list(schema)[len(keep) :], strict=True))], schema=schema)

    kinds = ", ".join(f"_k{i} {source.schema[f'_k{i}'].dataType.simpleString()}" for i in range(len(keep)))
    out = source.mapInArrow(trimmed(run), f"{kinds}, _lang_pred string, _score double, _noise double, _languages array<struct<lang:string,share:double>>")
    return out.select(*(F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)), "_lang_pred", "_score", "_noise", "_languages")
