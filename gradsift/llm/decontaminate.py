"""Benchmark passages in documents, found by a Wu-Manber search over words.

Patterns are runs of 13 words of the items (a shorter item is one pattern), in classes of
equal length. For each class a shift table over pairs of words says how far a window may
move without missing a pattern; where it says 0, the hash of the window's last words selects
a bucket of patterns, and the words themselves are compared. Windows move past positions
where no pattern can end.

The items are read in blocks of bounded size; each block is searched in all documents, so
the tables an executor holds don't grow with the benchmark.

Defined results: a null text or item has no words; an item of fewer words, but not none, is
one pattern; equal items each count; rows that repeat a document's id are searched one by
one; with no items nothing is hit.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from gradsift.llm.bytescan import ALNUM_SPLIT, chunks
from gradsift.llm.memory import trimmed
from gradsift.llm.staging import Stage

WINDOW = 13
#: Bytes of item text searched at once.
ITEM_BLOCK_BYTES = 8 << 20
_SHIFT_BITS = 18


def item_words(text: str | None) -> list[bytes]:
    """The contract's words of one text."""
    out = []
    for c in chunks(pa.array([text or ""])):
        c.words(ALNUM_SPLIT)
        raw = c.data.tobytes().lower()
        out += [raw[a:b] for a, b in zip(c.starts.tolist(), c.ends.tolist(), strict=True)]
    return out


class PatternClass:
    """Tables for patterns of one length."""

    def __init__(self, length: int):
        self.length, self.span = length, min(2, length)
        self.owners: dict[tuple[bytes, ...], set[int]] = defaultdict(set)

    def build(self, hash_words) -> None:
        """shift: words to move for each hashed block; buckets: patterns by the block they end with."""
        m, b = self.length, self.span
        self.shift = np.full(1 << _SHIFT_BITS, m - b + 1, dtype=np.uint8 if m < 200 else np.uint16)
        self.buckets: dict[int, list[tuple[bytes, ...]]] = defaultdict(list)
        patterns = sorted(self.owners)
        hashes = hash_words([w for p in patterns for w in p]).reshape(len(patterns), m)
        for j in range(b - 1, m):
            block = block_hash(hashes[:, j - b + 1 : j + 1])
            np.minimum.at(self.shift, block, m - 1 - j)
        for p, k in zip(patterns, block_hash(hashes[:, m - b :]).tolist(), strict=True):
            self.buckets[k].append(p)

    def search(self, blocks: np.ndarray, words, n: int) -> Iterator[tuple[int, tuple[bytes, ...]]]:
        """Places of patterns in a text of n words. blocks[j]: hash of the block that ends with word j."""
        m = self.length
        if n < m:
            return
        shift = self.shift[blocks]
        if shift[m - 1 : n].all():  # no block of the text ends a pattern
            return
        steps, j = shift.tolist(), m - 1
        while j < n:
            move = steps[j]
            if move:
                j += move
                continue
            for p in self.buckets.get(int(blocks[j]), ()):
                if words(j - m + 1, j + 1) == p:
                    yield j - m + 1, p
            j += 1


def block_hash(hashes: np.ndarray) -> np.ndarray:
    """Of the last axis: one or two words, to the index of a shift table."""
    x = hashes[..., -1]
    if hashes.shape[-1] == 2:
        x = x + (hashes[..., 0] ^ (hashes[..., 0] >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return ((x * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(64 - _SHIFT_BITS)).astype(np.int64)


def hash_words(words: list[bytes]) -> np.ndarray:
    """As a chunk hashes its words."""
    out = [np.zeros(0, dtype=np.uint64)]
    for c in chunks(pa.array([b" ".join(words).decode("utf-8", "surrogateescape")], pa.string()) if words else pa.array([], pa.string())):
        c.words(ALNUM_SPLIT)
        out.append(c.word_hashes())
    return np.concatenate(out)


class Patterns:
    """Search tables for a block of items."""

    def __init__(self, items: list[tuple[str, str | None]], window: int = WINDOW):
        self.ids = [i for i, _ in items]
        by_length: dict[int, PatternClass] = {}
        for k, (_, text) in enumerate(items):
            ws = item_words(text)
            m = min(window, len(ws))
            for at in range(len(ws) - m + 1 if m else 0):
                by_length.setdefault(m, PatternClass(m)).owners[tuple(ws[at : at + m])].add(k)
        self.classes = [by_length[m] for m in sorted(by_length)]
        for c in self.classes:
            c.build(hash_words)

    def scan(self, texts: pa.Array) -> Iterator[tuple[int, list[tuple[int, int]], set[int]]]:
        """For each text: its words, the hit runs of words, and the items that occur."""
        for c in chunks(texts):
            c.words(ALNUM_SPLIT)
            hashes = c.word_hashes()
            pairs = np.zeros(len(hashes), dtype=np.int64)
            if len(hashes) > 1:
                pairs[1:] = block_hash(np.stack([hashes[:-1], hashes[1:]], axis=1))
            ones = block_hash(hashes[:, None])
            raw = c.data.tobytes().lower()
            for d in range(len(c)):
                lo, hi = int(c.word_at[d]), int(c.word_at[d + 1])
                runs, found = [], set()

                def words(a: int, b: int, lo: int = lo) -> tuple[bytes, ...]:
                    return tuple(raw[s:e] for s, e in zip(c.starts[lo + a : lo + b].tolist(), c.ends[lo + a : lo + b].tolist(), strict=True))

                for k in self.classes:
                    for at, p in k.search((pairs if k.span == 2 else ones)[lo:hi], words, hi - lo):
                        runs.append((at, at + k.length))
                        found |= k.owners[p]
                yield hi - lo, runs, found


def _blocks(items: DataFrame, id_col: str, text_col: str, limit: int) -> Iterator[list[tuple[str, str | None]]]:
    block, size = [], 0
    for r in items.select(F.col(id_col).cast("string").alias("i"), F.col(text_col).alias("t")).toLocalIterator():
        block.append((r["i"], r["t"]))
        size += len(r["t"] or "") + 64
        if size >= limit:
            yield block
            block, size = [], 0
    if block:
        yield block


def find_contamination(docs: DataFrame, items: DataFrame, text_col: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, block_bytes: int = ITEM_BLOCK_BYTES, keep: list[str] | None = None) -> DataFrame:
    """The kept columns (doc_id, if None), n_words, hit_runs and items, for each row.

    hit_runs are the runs [a, b) of hit words, items the ids of the occurring items. Of a
    benchmark of several blocks, two at a time are on the driver.
    """
    spark, keep = docs.sparkSession, keep or ["doc_id"]
    source = docs.select(F.col(text_col).alias("_text"), *(F.col(f"`{c}`").alias(f"_k{i}") for i, c in enumerate(keep)))
    source = source.withColumn("_row", F.monotonically_increasing_id())
    blocks = _blocks(items, item_id, item_text, block_bytes)
    block, later = next(blocks, []), next(blocks, None)
    if later is None:
        every = _search(source, spark.sparkContext.broadcast(block), window)
    else:
        # rows are numbered once, and written, so that all passes number them alike
        stage = Stage(spark, "contamination")
        source, every = stage.put(source), None
        while block is not None:
            shared = spark.sparkContext.broadcast(block)
            found = _search(source, shared, window)
            part = stage.put(found if every is None else found.where(F.size("hit_runs") > 0))
            shared.destroy()
            every = part if every is None else every.unionByName(part)
            block, later = later, next(blocks, None)
        kept = [F.first(f"_k{i}").alias(f"_k{i}") for i in range(len(keep))]
        every = every.groupBy("_row").agg(
            *kept, F.first("n_words").alias("n_words"), F.flatten(F.collect_list("hit_runs")).alias("hit_runs"),
            F.flatten(F.collect_list("items")).alias("items"),
        )
    return every.select(*(F.col(f"_k{i}").alias(c) for i, c in enumerate(keep)), "n_words", "hit_runs", "items")


_LAST: list = [None, None]


def _search(source: DataFrame, shared, window: int) -> DataFrame:
    """A pass over the texts, the first column, with the tables of one block of items."""
    keep = source.columns[1:]
    schema = pa.schema(
        [(c, to_arrow_type(source.schema[c].dataType)) for c in keep]
        + [("n_words", pa.int64()), ("hit_runs", pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())]))), ("items", pa.list_(pa.string()))]
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if _LAST[0] is not shared.value:
            _LAST[:] = shared.value, Patterns(shared.value, window)
        patterns = _LAST[1]
        for batch in batches:
            n_words, runs, items = [], [], []
            for n, r, f in patterns.scan(batch.column(0)):
                n_words.append(n)
                runs.append([{"a": a, "b": b} for a, b in r])
                items.append([patterns.ids[k] for k in f])
            made = [pa.array(v, schema.field(k).type) for k, v in (("n_words", n_words), ("hit_runs", runs), ("items", items))]
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], *made], schema=schema)

    kinds = "".join(f"{c} {source.schema[c].dataType.simpleString()}, " for c in keep)
    return source.mapInArrow(trimmed(run), kinds + "n_words long, hit_runs array<struct<a:int,b:int>>, items array<string>")


def covered(runs: Column) -> Column:
    """Number of words in at least one run."""
    ordered = F.array_sort(runs)
    merged = F.aggregate(
        ordered, F.struct(F.lit(0).alias("n"), F.lit(0).alias("to")),
        lambda acc, r: F.struct(
            (acc["n"] + F.greatest(F.lit(0), r["b"] - F.greatest(acc["to"], r["a"]))).alias("n"),
            F.greatest(acc["to"], r["b"]).alias("to"),
        ),
    )
    return merged["n"].cast("long")


def digest(found: DataFrame, keep: list[str] | None = None, share: int = 20) -> DataFrame:
    """n_hit, n_items, items_sha256 and contaminated of find_contamination's rows."""
    items = F.array_sort(F.array_distinct("items"))
    n_hit = covered(F.col("hit_runs"))
    return found.select(
        *(keep or ["doc_id"]), "n_words", n_hit.alias("n_hit"), F.size(items).cast("long").alias("n_items"),
        F.sha2(F.array_join(items, ","), 256).alias("items_sha256"),
    ).withColumn("contaminated", (F.col("n_hit") > 0) & (F.lit(share) * F.col("n_hit") >= F.col("n_words")))


def brute_force(docs: list[tuple[object, str | None]], items: list[tuple[str, str | None]], window: int = WINDOW) -> list[tuple]:
    """The contract word by word, for tests."""
    windows = defaultdict(set)
    for i, text in items:
        ws = item_words(text)
        m = min(window, len(ws))
        for at in range(len(ws) - m + 1 if m else 0):
            windows[tuple(ws[at : at + m])].add(str(i))
    lengths = {len(w) for w in windows}
    out = []
    for i, text in docs:
        ws, hit, found = item_words(text), set(), set()
        for m in lengths:
            for at in range(len(ws) - m + 1):
                own = windows.get(tuple(ws[at : at + m]))
                if own:
                    hit.update(range(at, at + m))
                    found |= own
        sha = hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()
        out.append((i, len(ws), len(hit), len(found), sha, bool(hit) and 20 * len(hit) >= len(ws)))
    return out
