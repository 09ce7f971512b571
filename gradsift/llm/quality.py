"""Quality rules whose cutoffs follow the data: thresholds from mergeable quantile sketches.

Each document gets counts over its whole text. For each measure a sketch counts documents in
buckets of equal relative width, by language and source; sketches of equal buckets merge by
adding, so partial sums go map-side and a language's or the corpus's sketch is the sum of
its parts. A measure's limit stands beyond its third quartile by a power of the quartiles'
ratio, so it follows the level and the spread of the group's own documents; a group too
small for quartiles takes its language's limit, and a language too small the corpus's, and
no group's is above its language's. Limits are joined back on language and source.

Defined results: a null text has no words and fails the base rules; a null language or
source is a group of its own; an empty table has no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gradsift.llm.bytescan import BLANK_SPLIT, byte_class, chunks, mix64
from gradsift.llm.staging import Stage

_SYMBOLS = ~byte_class("#*$%&|<>")
_BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _equal_before(keys: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """For each owner, how many of its keys equal an earlier one."""
    if not len(keys):
        return np.zeros(n, dtype=np.int64)
    order = np.lexsort((keys, owner))
    k, o = keys[order], owner[order]
    same = (k[1:] == k[:-1]) & (o[1:] == o[:-1])
    return np.bincount(o[1:][same], minlength=n)


def count_text(texts: pa.Array) -> Iterator[np.ndarray]:
    """The base counts, a row for each text."""
    for c in chunks(texts):
        c.words(BLANK_SPLIT)
        n, data = len(c), c.data
        begins = (data & 0xC0) != 0x80
        n_words = np.diff(c.word_at)
        word_chars = c.sums(begins & BLANK_SPLIT[data])
        n_symbols = c.sums(_SYMBOLS[data])

        # lines: cut at each \n and at the texts' ends
        cuts = np.flatnonzero(data == 10)
        starts = np.sort(np.concatenate([c.offsets[:-1], cuts + 1]), kind="stable")
        ends = np.sort(np.concatenate([cuts, c.offsets[1:]]), kind="stable")
        owner = np.repeat(np.arange(n), c.sums(data == 10) + 1)
        order = np.lexsort((starts, owner)) if n > 1 else np.arange(len(starts))
        starts, ends = starts[order], ends[order]
        has_word = np.searchsorted(c.starts, starts) < np.searchsorted(c.starts, ends)
        starts, ends, owner = starts[has_word], ends[has_word], owner[has_word]
        n_dup_lines = _equal_before(c.span_hashes(starts, ends, fold=False), owner, n)

        # windows of five words found again
        windows, at = c.shingles(5, fold=False, short=False)
        owner = np.repeat(np.arange(n), np.diff(at))
        keyed = mix64(windows ^ (owner.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
        order = np.argsort(keyed, kind="stable")
        k = keyed[order]
        again = np.zeros(len(k), dtype=bool)
        if len(k):
            same = k[1:] == k[:-1]
            again[1:] |= same
            again[:-1] |= same
        first = c.word_at[owner[order[again]]] + order[again] - at[owner[order[again]]]
        cover = np.zeros(len(c.starts) + 1, dtype=np.int64)
        np.add.at(cover, first, 1)
        np.add.at(cover, first + 5, -1)
        covered = np.concatenate([[0], np.cumsum(np.cumsum(cover[:-1]) > 0)])
        n_repeat = covered[c.word_at[1:]] - covered[c.word_at[:-1]]
        yield np.stack([n_words, word_chars, n_symbols, n_dup_lines, n_repeat], axis=1)


def base_counts(docs: DataFrame, text_col: str = "text", keep: tuple[str, ...] = ("doc_id", "lang", "source")) -> DataFrame:
    """The kept columns and the base counts of each row."""
    names = [f"k{i}" for i in range(len(keep))]
    source = docs.select(F.col(text_col).alias("_text"), *(F.col(c).alias(a) for c, a in zip(keep, names, strict=True)))
    kinds = ", ".join(f"{a} {source.schema[a].dataType.simpleString()}" for a in names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = np.concatenate([np.zeros((0, 5), dtype=np.int64), *count_text(batch.column(0))])
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], *(pa.array(rows[:, i]) for i in range(5))], names=[*names, *_BASE])

    out = source.mapInArrow(run, f"{kinds}, " + ", ".join(f"{b} long" for b in _BASE))
    return out.withColumnsRenamed(dict(zip(names, keep, strict=True)))


#: Growth of bucket bounds: a sketch's quantile is off by at most 2 %.
GAMMA = 1.02
_SCALE = 10_000


def bucket(ratio: Column) -> Column:
    """Index of the sketch bucket of a value of at least 0; 0 for less than 1/10000."""
    scaled = F.greatest(ratio * _SCALE, F.lit(0.0))
    return F.when(scaled < 1, F.lit(0)).otherwise(F.floor(F.log(scaled) / float(np.log(GAMMA))) + 1).cast("int")


def bucket_value(index: Column) -> Column:
    """The upper bound of a bucket."""
    return F.pow(F.lit(GAMMA), index) / _SCALE


def sketch(table: DataFrame, keys: list[str], measures: dict[str, Column]) -> DataFrame:
    """(keys, measure, bucket, n): one row a bucket, mergeable by sum(n)."""
    pairs = F.explode(F.array(*(F.struct(F.lit(m).alias("m"), bucket(c).alias("b")) for m, c in measures.items())))
    return (
        table.select(*keys, pairs.alias("_p"))
        .groupBy(*keys, F.col("_p.m").alias("measure"), F.col("_p.b").alias("bucket"))
        .agg(F.count(F.lit(1)).alias("n"))
    )


def merge(sketches: DataFrame, keys: list[str]) -> DataFrame:
    """Sketches with fewer keys."""
    return sketches.groupBy(*keys, "measure", "bucket").agg(F.sum("n").alias("n"))


def quantiles(sketches: DataFrame, keys: list[str], at: dict[str, float]) -> DataFrame:
    """The bucket of each quantile, and docs: the documents in the sketch."""
    group = Window.partitionBy(*keys, "measure")
    ranked = sketches.withColumn("_upto", F.sum("n").over(group.orderBy("bucket"))).withColumn("docs", F.sum("n").over(group))
    return ranked.groupBy(*keys, "measure", "docs").agg(
        *(F.min(F.when(F.col("_upto") >= q * F.col("docs"), F.col("bucket"))).alias(name) for name, q in at.items())
    )


@dataclass(frozen=True)
class Rule:
    """A measure, and how many quartile distances beyond the quartiles its fences stand.

    Distances are in buckets, so fences stand by factors: a measure's limit is its third
    quartile times a power of the ratio of the quartiles. least: the distance that is taken
    where the quartiles are closer, as with equal documents.
    """

    value: Column
    reach: int
    least: int


def rules() -> dict[str, Rule]:
    """Rates have half an event added, so that none in a long text is a lower rate than none in a short one."""

    def rate(n: str, of: str) -> Column:
        return (F.col(n) + 0.5) / (F.col(of) + 1)

    return {
        "symbols": Rule(rate("n_symbols", "word_chars"), 3, 35),
        "repeats": Rule(rate("n_repeat_words", "n_words"), 3, 35),
        "dup_lines": Rule(rate("n_dup_lines", "n_words"), 3, 35),
        "word_length": Rule(F.col("word_chars") / F.greatest(F.col("n_words"), F.lit(1)), 6, 2),
    }


def fences(sketches: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, measure, docs, high, low): the last buckets that pass."""
    q = quantiles(sketches, keys, {"q1": 0.25, "q3": 0.75})
    of = rules()

    def by_measure(x: dict[str, int]) -> Column:
        return F.element_at(F.create_map(*(F.lit(v) for kv in x.items() for v in kv)), F.col("measure"))

    width = by_measure({m: r.reach for m, r in of.items()}) * F.greatest(F.col("q3") - F.col("q1"), by_measure({m: r.least for m, r in of.items()}))
    return q.select(*keys, "measure", "docs", (F.col("q3") + width).alias("high"), (F.col("q1") - width).alias("low"))


def limits(counts: DataFrame, min_docs: int = 50) -> DataFrame:
    """A row for each language and source, with <measure>_high and, for word_length, _low, as buckets."""
    own = sketch(counts.where(F.col("n_words") > 0), ["lang", "source"], {m: r.value for m, r in rules().items()})
    by_lang = merge(own, ["lang"])
    everything = merge(by_lang, [])
    a = fences(own, ["lang", "source"])
    b = fences(by_lang, ["lang"]).select(F.col("lang").alias("_l"), F.col("measure").alias("_m"), F.col("docs").alias("_d2"), F.col("high").alias("_h2"), F.col("low").alias("_l2"))
    c = fences(everything, []).select(F.col("measure").alias("_m3"), F.col("high").alias("_h3"), F.col("low").alias("_l3"))
    joined = a.join(b, a["lang"].eqNullSafe(b["_l"]) & (a["measure"] == b["_m"])).join(F.broadcast(c), F.col("measure") == F.col("_m3"))

    def wider(y: str, z: str) -> Column:
        return F.when(F.col("_d2") >= min_docs, F.col(y)).otherwise(F.col(z))

    def level(x: str, y: str, z: str) -> Column:
        return F.when(F.col("docs") >= min_docs, F.col(x)).otherwise(wider(y, z))

    # a source that is bad in large part widens its own fence, so its language's, or the corpus's, bounds it
    high = F.least(level("high", "_h2", "_h3"), wider("_h2", "_h3"))
    low = F.greatest(level("low", "_l2", "_l3"), wider("_l2", "_l3"))
    chosen = joined.select("lang", "source", "measure", high.alias("high"), low.alias("low"))
    picks = [F.max(F.when(F.col("measure") == m, F.col("high"))).alias(f"{m}_high") for m in rules()]
    return chosen.groupBy("lang", "source").agg(*picks, F.max(F.when(F.col("measure") == "word_length", F.col("low"))).alias("word_length_low"))


def judge(docs: DataFrame, text_col: str = "text", min_docs: int = 50) -> DataFrame:
    """doc_id, base counts, base_failed, kept, and the limits held against. docs: doc_id, text, lang, source."""
    stage = Stage(docs.sparkSession, "quality")
    counts = stage.put(base_counts(docs, text_col))
    cut = limits(counts, min_docs).withColumnsRenamed({"lang": "_lang", "source": "_source"})
    base_failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    own = {m: bucket(r.value) for m, r in rules().items()}
    ok = own["word_length"] >= F.col("word_length_low")
    for m, b in own.items():
        ok = ok & (b <= F.col(f"{m}_high"))
    # a document without words is in no sketch, and fails the base rules
    kept = ~base_failed & F.coalesce(ok, F.lit(False))
    return (
        counts.join(cut, counts["lang"].eqNullSafe(cut["_lang"]) & counts["source"].eqNullSafe(cut["_source"]), "left")
        .select("doc_id", *_BASE, base_failed.alias("base_failed"), kept.alias("kept"), *(bucket_value(F.col(f"{m}_high")).alias(f"{m}_high") for m in own))
    )
