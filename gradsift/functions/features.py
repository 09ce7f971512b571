"""Pooled sample features: text statistics and raster pools."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from string import ascii_uppercase, digits

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TEXT_FEATURES = ("log_chars", "upper", "distinct", "symbols", "digits", "word_chars")
#: Centre and scale of each text statistic for the fixed raters.
CENTRES = (7.0, 0.05, 0.70, 0.02, 0.01, 6.0)
SCALES = (1.0, 0.10, 0.20, 0.05, 0.02, 2.0)


def text_statistics(text: Column) -> dict[str, Column]:
    """Six statistics of a text; those of an empty text are 0."""
    t = F.coalesce(text, F.lit(""))
    n = F.char_length(t)
    chars = F.greatest(n, F.lit(1)).cast("double")
    words = F.array_remove(F.split(F.replace(t, F.lit("\n"), F.lit(" ")), " "), "")
    n_words = F.greatest(F.size(words), F.lit(1)).cast("double")

    def share(characters: str) -> Column:
        return (n - F.char_length(F.translate(t, characters, ""))) / chars

    return {
        "log_chars": F.log1p(n.cast("double")),
        "upper": share(ascii_uppercase),
        "distinct": F.size(F.array_distinct(words)) / n_words,
        "symbols": share("#*$%&|<>"),
        "digits": share(digits),
        "word_chars": n / n_words,
    }


def pool_text(df: DataFrame, text_col: str = "text", standardise: bool = True) -> DataFrame:
    """Adds features array<double>: the statistics, on the fixed scale if standardise."""
    stats = text_statistics(F.col(text_col))
    cols = [(stats[k] - F.lit(c)) / F.lit(s) if standardise else stats[k] for k, c, s in zip(TEXT_FEATURES, CENTRES, SCALES, strict=True)]
    return df.withColumn("features", F.array(*cols))


def standardise_by_corpus(df: DataFrame, features: str, d: int) -> DataFrame:
    """Features less the corpus mean, over the corpus deviation: one aggregate of 2d numbers, broadcast."""
    aggs = [F.avg(F.col(features)[i]).alias(f"m{i}") for i in range(d)] + [F.stddev_pop(F.col(features)[i]).alias(f"s{i}") for i in range(d)]
    stats = df.agg(*aggs)
    out = df.crossJoin(F.broadcast(stats))
    z = [F.when(F.col(f"s{i}") > 0, (F.col(features)[i] - F.col(f"m{i}")) / F.col(f"s{i}")).otherwise(F.lit(0.0)) for i in range(d)]
    return out.withColumn(features, F.array(*z)).drop(*[f"{k}{i}" for k in "ms" for i in range(d)])


def raster(vector: Column) -> Column:
    """Stored floats as doubles."""
    return F.transform(vector, lambda x: x.cast("double"))


def pool_raster(pixels: Column, side: int, to: int) -> Column:
    """Mean pool of a side x side raster to to x to cells, row by row."""
    step = side // to
    cells = [
        [pixels[(r * step + i) * side + c * step + j] for i in range(step) for j in range(step)]
        for r in range(to) for c in range(to)
    ]

    def mean(xs: list[Column]) -> Column:
        total = xs[0]
        for x in xs[1:]:
            total = total + x
        return total / F.lit(float(len(xs)))

    return F.array(*(mean(xs) for xs in cells))


def raster_features(pixels: Column) -> Column:
    """Pooled 2 x 2 means, then mean and deviation of all cells, of an 8 x 8 raster."""
    n = F.size(pixels)
    mean = F.aggregate(pixels, F.lit(0.0), lambda a, x: a + x) / n
    square = F.aggregate(pixels, F.lit(0.0), lambda a, x: a + x * x) / n
    return F.concat(pool_raster(pixels, 8, 2), F.array(mean, F.sqrt(F.greatest(square - mean * mean, F.lit(0.0)))))


#: Vocabularies of the character proxy. 8: vowel, consonant, capital, non-ASCII, digit, space, newline, other.
#: 32: a letter each, capital, digit, space, newline, non-ASCII, other. 128: the ASCII code, capped.
VOCABULARIES = (8, 32, 128)


@lru_cache(maxsize=3)
def class_table(vocab: int) -> np.ndarray:
    """Class of each code point below 128; the last entry is for those above."""
    code = np.arange(129)
    low, high, digit = (code >= 97) & (code <= 122), (code >= 65) & (code <= 90), (code >= 48) & (code <= 57)
    if vocab == 8:
        vowel = np.isin(code, [*map(ord, "aeiou")])
        return np.select([vowel, low, high, code == 128, digit, code == 32, code == 10], range(7), 7)
    if vocab == 32:
        return np.select([low, high, digit, code == 32, code == 10, code == 128], [code - 97, 26, 27, 28, 29, 30], 31)
    if vocab == 128:
        return np.minimum(code, 127)
    raise ValueError(f"no classes for a vocabulary of {vocab}")


def text_classes(text: str | None, vocab: int) -> np.ndarray:
    points = np.frombuffer((text or "").encode("utf-32-le"), dtype="<u4")
    return class_table(vocab)[np.minimum(points, 128)]


def bigram_profile(text: str | None, vocab: int) -> tuple[np.ndarray, np.ndarray]:
    """(cells, counts): transitions from class a to b are cell a * vocab + b."""
    c = text_classes(text, vocab)
    return np.unique(c[:-1] * vocab + c[1:], return_counts=True)


def bigram_counts(df: DataFrame, id_col: str, text_col: str, vocab: int = 32) -> DataFrame:
    """(id, a, b, n): how often class b follows class a in each text. No exchange."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [bigram_profile(t.as_py(), vocab) for t in batch.column(1)]
            sizes = np.array([len(cells) for cells, _ in found], dtype=np.int64)
            cells = np.concatenate([np.zeros(0, dtype=np.int64), *(c for c, _ in found)])
            counts = np.concatenate([np.zeros(0, dtype=np.int64), *(n for _, n in found)])
            ids = batch.column(0).take(pa.array(np.repeat(np.arange(len(batch)), sizes)))
            yield pa.RecordBatch.from_arrays([ids, pa.array((cells // vocab).astype(np.int32)), pa.array((cells % vocab).astype(np.int32)), pa.array(counts.astype(np.int64))], names=[id_col, "a", "b", "n"])

    return df.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, a int, b int, n long")


def hashed_word_bigrams(df: DataFrame, id_col: str, text_col: str, vocab: int = 32) -> DataFrame:
    """(id, a, b, n): how often a word of hash class b follows one of class a; words are cut at spaces and line ends."""
    words = F.filter(F.split(F.replace(F.lower(text_col), F.lit("\n"), F.lit(" ")), " "), lambda w: w != "")
    classes = F.transform(words, lambda w: (F.conv(F.substring(F.md5(w.cast("binary")), 1, 8), 16, 10).cast("long") % vocab).cast("int"))
    known = df.select(id_col, classes.alias("_c")).where(F.size("_c") > 1)
    pairs = F.arrays_zip(F.slice("_c", F.lit(1), F.size("_c") - 1).alias("a"), F.slice("_c", F.lit(2), F.size("_c") - 1).alias("b"))
    return known.select(id_col, F.explode(pairs).alias("_p")).groupBy(id_col, F.col("_p.a").alias("a"), F.col("_p.b").alias("b")).agg(F.count(F.lit(1)).alias("n"))
