"""Deterministic minibatches and splits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradsift.functions.hashing import hash32, hash_uniform
from gradsift.operators.ranking import rank_corpus, unused


def assign_batches(df: DataFrame, id_col: str, size: int = 64, epoch: int = 0, seed: int = 42, how: str = "hashed", n_batches: int | None = None) -> DataFrame:
    """Adds batch_id. hashed: no exchange, sizes vary; exact: by hash rank, size each but the last.

    hashed needs the number of batches, which a caller knows from an earlier count.
    """
    key = seed + epoch
    if how == "hashed":
        if not n_batches:
            n_batches = max(1, -(-df.count() // size))
        return df.withColumn("batch_id", hash32(id_col, key) % n_batches)
    if how == "exact":
        u, rank, pct = unused(df, "_u", "_rank", "_pct")
        ranked = rank_corpus(df.withColumn(u, hash_uniform(id_col, key)), u, id_col, descending=False, rank_col=rank, pct_col=pct)
        return ranked.withColumn("batch_id", F.floor((F.col(rank) - 1) / size)).drop(u, rank, pct)
    raise ValueError(f"no way {how!r} to make batches")


def split_of(id_col: str, seed: int = 7, validation: float = 0.1, test: float = 0.1) -> Column:
    u = hash_uniform(id_col, seed)
    return F.when(u < validation, F.lit("val")).when(u < validation + test, F.lit("test")).otherwise(F.lit("train"))


def hash_sample(df: DataFrame, id_col: str, share: float, seed: int) -> DataFrame:
    """A deterministic Bernoulli sample, which a retry repeats."""
    return df.where(hash_uniform(id_col, seed) < share)


def without_copies(train: DataFrame, held_out: DataFrame, text_col: str = "text") -> DataFrame:
    """Training rows whose text isn't a held-out text. The texts meet by digest."""
    keys = held_out.select(F.sha2(F.col(text_col).cast("binary"), 256).alias("_digest")).distinct()
    marked = train.withColumn("_digest", F.sha2(F.col(text_col).cast("binary"), 256))
    return marked.join(keys, "_digest", "left_anti").drop("_digest")


def dedup_exact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Of equal texts, the id that sorts first; null texts are equal. Only digests and ids are exchanged for the choice."""
    digest = F.sha2(F.coalesce(F.col(text_col), F.lit("\0")).cast("binary"), 256)
    first = docs.groupBy(digest.alias("_digest")).agg(F.min(id_col).alias("_first")).select("_first")
    return docs.join(first, docs[id_col].eqNullSafe(first["_first"]), "left_semi")
