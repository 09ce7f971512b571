"""Exact Jaccard self-join of documents on word shingles, by prefixes under several token orders.

Texts with equal shingle sets are one node. Two sets with a Jaccard similarity of at least t
share a token in the prefix of each, for any order of all tokens, if a prefix of a set of n
has n - ceil(t n) + 1 tokens. The orders are:

* a first one, in which the tokens of the lowest quarter of the hash range come first, those
  that no other set has before the shared ones. Only that quarter is counted for it, and most
  documents' prefixes have no shared token, so they link to nothing;
* by rarity, for what is left: all tokens are counted, and a set's prefix has its own tokens
  first, then the rarest shared ones. Its shared prefix tokens make pairs;
* by hash, upwards and downwards. A pair is a candidate only if it shares prefix tokens under
  both of these as well. Prefixes alone are compared for that; whole sets are fetched, and
  intersected, for the candidates that all orders leave.

Since a set's own tokens are in no intersection, comparing shared tokens and sizes is exact.

Only the classes are asked for, so links within a class need not all be found. First each
node is paired with one node of each prefix token, that with the fewest tokens of its own,
which is the middle of a group of copies or the barest carrier of a passage; a large group
takes pairs linear in its size. Then all pairs of different classes are filtered and compared
that can be similar enough, so that no class is left apart from one it links to. What two
sets have in common is at most what both share with the middle, as the smaller number, and
what both share with others, likewise; and so in each of 64 parts of the hash range. Sets of
a middle and class are ruled out together where they can be. Where a middle still has several classes, its sets that the
orders ruled out are measured against it for that bound; this never links anything.

Defined results: a text without words has an empty set and is alone; fewer words than a
shingle are one shingle; a null id is an id; an empty table has no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradsift.llm.bytescan import BLANK_SPLIT, chunks, mix64
from gradsift.llm.graph import components
from gradsift.llm.memory import trimmed
from gradsift.llm.staging import Stage

#: Parts of a set by hash, whose counts bound what two sets have in common.
_PARTS = 64
#: Hashes are 63 bits, so that they are positive in a signed column.
_COUNTED = 1 << 61
#: Bits of the filter for each key, and of the largest filter. More keys are joined, not broadcast.
_BITS_A_KEY = 16
MAX_BLOOM_BITS = 1 << 28


def shingle_sets(texts: pa.Array, k: int = 5) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    for c in chunks(texts):
        c.words(BLANK_SPLIT)
        hashes, at = c.shingles(k)
        hashes = (hashes >> np.uint64(1)).astype(np.int64)
        for d in range(len(c)):
            own = np.sort(hashes[at[d] : at[d + 1]])
            if len(own) > 1:
                keep = np.empty(len(own), dtype=bool)
                keep[0] = True
                np.not_equal(own[1:], own[:-1], out=keep[1:])
                own = own[keep]
            yield own


def set_key(tokens: np.ndarray) -> int:
    """A key of the set, whatever the order."""
    if not len(tokens):
        return 0
    return int(mix64(np.array([mix64(tokens.astype(np.uint64)).sum(dtype=np.uint64)], dtype=np.uint64))[0] >> np.uint64(1))


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1


def _profiles(docs: DataFrame, percent: int, k: int) -> DataFrame:
    """(id, key, n, counted, up, down): a row for each text; up and down end its prefixes by hash."""
    names = ["key", "n", "counted", "up", "down"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for s in shingle_sets(batch.column(1), k):
                n = len(s)
                p, v = prefix_length(n, percent), int(np.searchsorted(s, _COUNTED))
                rows.append((set_key(s), n, v, int(s[p - 1]) if n else 0, int(s[n - p]) if n else 0))
            cols = np.array(rows, dtype=np.int64).reshape(-1, 5)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(cols[:, i]) for i in range(5))], names=["id", *names])

    kind = docs.schema["id"].dataType.simpleString()
    return docs.select("id", "text").mapInArrow(trimmed(run), f"id {kind}, " + ", ".join(f"{x} long" for x in names))


def _tokens(docs: DataFrame, percent: int, k: int, bloom=None, every: bool = False) -> DataFrame:
    """(token, key): of each set the counted tokens, or its prefix by hash if that is longer.

    With a filter of keys: all tokens of the sets in it; with every: of all sets. A task
    leaves out texts whose set its batch has had.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = None if bloom is None else bloom.value
        for batch in batches:
            seen, tokens, keys = set(), [], []
            for s in shingle_sets(batch.column(0), k):
                key = set_key(s)
                if not len(s) or key in seen or bits is not None and not in_filter(bits, key):
                    continue
                seen.add(key)
                m = len(s) if every or bits is not None else max(prefix_length(len(s), percent), int(np.searchsorted(s, _COUNTED)))
                tokens.append(s[:m])
                keys.append(np.full(m, key, dtype=np.int64))
            if tokens:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(tokens)), pa.array(np.concatenate(keys))], names=["token", "key"])

    return docs.select("text").mapInArrow(trimmed(run), "token long, key long")


def _keyed_texts(docs: DataFrame, k: int) -> DataFrame:
    """(key, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = [set_key(s) for s in shingle_sets(batch.column(0), k)]
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), batch.column(0)], names=["key", "text"])

    return docs.select("text").mapInArrow(trimmed(run), "key long, text string")


def bloom_bits(n: int) -> int:
    """A power of two with 16 bits a key, from 2**20 on."""
    return max(1 << 20, 1 << (_BITS_A_KEY * n - 1).bit_length())


def _places(key, bits: int):
    """The two bits of a key; of a column or a number."""
    return key % bits, (F.shiftright(key, 30) if isinstance(key, Column) else key >> 30) % bits


def _bloom(keys: DataFrame, bits: int) -> np.ndarray:
    """A Bloom filter of the keys, as words of 32 bits; at most as many rows reach the driver."""
    words = keys.select(F.explode(F.array(*_places(F.col("key"), bits))).alias("p")).groupBy(F.shiftright("p", 5).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, CAST(p % 32 AS INT))")).alias("bits"))
    out = np.zeros(bits // 32, dtype=np.uint32)
    rows = words.toPandas()
    out[rows["w"].to_numpy(dtype=np.int64)] = rows["bits"].to_numpy(dtype=np.int64)
    return out


def in_filter(bits: np.ndarray, key: int) -> bool:
    return all(int(bits[x >> 5]) >> (x & 31) & 1 for x in _places(key, 32 * len(bits)))


class JaccardClasses:
    """The join's steps over one table; percent: the least similarity in hundredths."""

    def __init__(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 80, k: int = 5, max_bits: int = MAX_BLOOM_BITS):
        self.percent, self.k, self.max_bits = percent, k, max_bits
        self.docs = docs.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{text_col}`").alias("text"))
        self.stage = Stage(docs.sparkSession, "jaccard")
        self.profiles = self.stage.put(_profiles(self.docs, percent, k))
        self.nodes = self.profiles.where("n > 0").groupBy("key", "n", "counted", "up", "down").agg(F.min("id").alias("least"))
        #: pairs of the rarity order, and those that the orders by hash leave, by step
        self.report: dict[str, tuple[DataFrame, DataFrame]] = {}

    def shared(self, tokens: DataFrame) -> DataFrame:
        """(token, df) of the tokens that at least two sets have."""
        counted = tokens.groupBy("token").agg(F.min("key").alias("lo"), F.max("key").alias("hi"), F.count(F.lit(1)).alias("df"))
        return counted.where("lo <> hi").select("token", "df")

    def first_order(self) -> DataFrame:
        """Keys whose prefix under the first order has a shared token."""
        tokens = _tokens(self.docs, self.percent, self.k)
        found = tokens.join(self.shared(tokens), "token").groupBy("key").agg(F.collect_set("token").alias("found"))
        seen = F.size(F.filter("found", lambda x: x < _COUNTED))
        return found.select("key", seen.alias("seen")).join(self.nodes, "key").where(F.col("counted") - F.col("seen") < self.p).select("key")

    @property
    def p(self) -> Column:
        return F.expr(f"n - CAST(ceil({self.percent} * n / 100) AS BIGINT) + 1")

    def shared_tokens(self) -> DataFrame:
        """(key, least, n, c, up, down, tokens, prefix) of the nodes left: tokens are the c shared ones."""
        keys = self.stage.put(self.first_order())
        bits = bloom_bits(keys.count())
        if bits <= self.max_bits:
            bloom = self.docs.sparkSession.sparkContext.broadcast(_bloom(keys, bits))
            tokens = _tokens(self.docs, self.percent, self.k, bloom)
        else:
            tokens = _tokens(_keyed_texts(self.docs, self.k).join(keys, "key", "left_semi"), self.percent, self.k, every=True)
        self.stage.sweep()
        # the order only has to be one: a token's count is taken once, and written
        counted = self.stage.put(self.shared(tokens))
        found = (
            tokens.join(counted, "token").groupBy("key").agg(F.array_sort(F.collect_set(F.struct("df", "token"))).alias("found"))
            .withColumn("c", F.size("found").cast("long"))
        )
        left = found.join(self.nodes, "key").withColumn("take", self.p - (F.col("n") - F.col("c"))).where("take > 0")
        token = lambda x: x["token"]
        out = self.stage.put(left.select(
            "key", "least", "n", "c", "up", "down", F.transform("found", token).alias("tokens"),
            F.transform(F.slice("found", F.lit(1), F.col("take").cast("int")), token).alias("prefix"),
        ))
        self.stage.drop(counted, keys)
        return out

    def sides(self, pairs: DataFrame, own: DataFrame, *columns: Column) -> DataFrame:
        """The pairs (a, b) with columns of both sides, named after their side."""
        for x in "ab":
            side = own.select(F.col("key").alias(x), *columns)
            pairs = pairs.join(side.withColumnsRenamed({c: f"{c}_{x}" for c in side.columns[1:]}), x)
        return pairs

    def candidates(self, pairs: DataFrame, own: DataFrame) -> DataFrame:
        """The pairs (a, b) that share prefix tokens under the orders by hash too. Whole sets aren't compared."""
        rising = F.filter("tokens", lambda x: x <= F.col("up")).alias("rising")
        falling = F.filter("tokens", lambda x: x >= F.col("down")).alias("falling")
        both = self.sides(pairs.select("a", "b"), own, rising, falling)
        return both.where(F.arrays_overlap("rising_a", "rising_b") & F.arrays_overlap("falling_a", "falling_b")).select("a", "b")

    def common(self, pairs: DataFrame, own: DataFrame) -> DataFrame:
        """(a, b, n_a, n_b, i): i is the size of the intersection."""
        both = self.sides(pairs.select("a", "b"), own, F.col("n"), F.col("tokens"))
        return both.select("a", "b", "n_a", "n_b", F.size(F.array_intersect("tokens_a", "tokens_b")).cast("long").alias("i"))

    def verified(self, step: str, pairs: DataFrame, own: DataFrame) -> DataFrame:
        """(a, b, i, linked) of the pairs that all orders leave: linked are the similar ones."""
        pairs = self.stage.put(pairs)
        left = self.stage.put(self.candidates(pairs, own))
        self.report[step] = pairs, left
        return self.common(left, own).select("a", "b", "i", (100 * F.col("i") >= self.percent * (F.col("n_a") + F.col("n_b") - F.col("i"))).alias("linked"))

    def run(self) -> DataFrame:
        """(id, n_shingles, component_id) of every row."""
        stage, own = self.stage, self.shared_tokens()
        stage.sweep()
        held = stage.put(own.select("key", "least", "n", "c", F.explode("prefix").alias("token")))
        barest = F.min(F.struct((F.col("n") - F.col("c")).alias("own"), "least", "key")).alias("f")
        middles = held.groupBy("token").agg(barest, F.count(F.lit(1)).alias("_sets")).where("_sets > 1").select("token", F.col("f.key").alias("middle"))
        starred = stage.put(held.join(middles, "token").select("token", "key", "n", "c", "middle"))
        stars = starred.where("key <> middle").select(F.col("key").alias("a"), F.col("middle").alias("b")).distinct()
        near = stage.put(self.verified("middles", stars, own))
        stage.sweep()
        edges = near.where("linked").select("a", "b")
        joined = stage.put(components(edges, stage))

        # candidates between different classes
        common = near.select(F.col("a").alias("key"), F.col("b").alias("middle"), "i")
        marked = (
            starred.join(joined.select(F.col("node").alias("key"), "comp"), "key", "left").join(common, ["key", "middle"], "left")
            .select("middle", "key", "n", "c", F.coalesce("comp", "key").alias("comp"), F.when(F.col("key") == F.col("middle"), F.col("c")).otherwise(F.col("i")).alias("i")).distinct()
        )
        several = stage.put(self.live(marked))
        ruled_out = several.where("i IS NULL").select(F.col("key").alias("a"), F.col("middle").alias("b"))
        bound = self.common(ruled_out, own).select(F.col("a").alias("key"), F.col("b").alias("middle"), F.col("i").alias("_bound"))
        live = self.live(several.join(bound, ["key", "middle"], "left").withColumn("i", F.coalesce("i", "_bound")).select(marked.columns))
        parts = F.transform(F.sequence(F.lit(0), F.lit(_PARTS - 1)), lambda b: F.size(F.filter("tokens", lambda t: t % _PARTS == b)))
        live = stage.put(live.join(own.join(several.select("key").distinct(), "key", "left_semi").select("key", parts.alias("parts")), "key"))
        more = stage.put(self.verified("classes", self.possible(live), own).where("linked").select("a", "b"))
        final = stage.put(components(edges.unionByName(more), stage))

        least = self.nodes.select("key", "least").join(final.select(F.col("node").alias("key"), "comp"), "key", "left").withColumn("comp", F.coalesce("comp", "key"))
        names = least.groupBy("comp").agg(F.min("least").alias("component_id"))
        of_key = least.join(names, "comp").select("key", "component_id")
        out = (
            self.profiles.join(of_key, "key", "left")
            .select("id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("id")).alias("component_id"))
        )
        stage.drop(own, held, starred, near, joined, several, live, more)
        return out

    def live(self, marked: DataFrame) -> DataFrame:
        """Rows of middles with several classes, but for sets that none of the middle's sizes allows."""
        span = marked.groupBy("middle").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.min("n").alias("least_n")).where("lo <> hi")
        nearest = F.greatest(F.col("least_n"), F.ceil(F.col("n") * self.percent / 100))
        return marked.join(span, "middle").where((100 + self.percent) * F.col("c") >= self.percent * (F.col("n") + nearest)).select(marked.columns)

    def possible(self, live: DataFrame) -> DataFrame:
        """Pairs (a, b) of a middle's sets in different classes that can be similar enough.

        Sets with a common prefix token have its middle in common, so these are all candidates.
        First come the pairs of shapes (size, shared tokens, those shared with the middle) that
        a middle has, then the classes that have them, then the classes' sets. Classes and sets
        meet only if their tokens, counted in parts by hash, can be enough in common: part by
        part, two sets share at most the smaller count, and two classes the smaller of their
        highest counts. Pairs that aren't so near as that are never made.
        """
        shape = ["n", "c", "i"]

        def of(side: str, *columns: str) -> DataFrame:
            return live.select("middle", *columns, *(F.col(c).alias(f"{c}_{side}") for c in shape))

        def classes_of(side: str) -> DataFrame:
            most = F.array(*(F.max(F.get("parts", F.lit(b))) for b in range(_PARTS))).alias(f"parts_{side}")
            return of(side, "comp", "parts").groupBy("middle", *(f"{c}_{side}" for c in shape), F.col("comp").alias(f"comp_{side}")).agg(most)

        def sets_of(side: str, name: str) -> DataFrame:
            return of(side, "comp", "key", "parts").withColumnsRenamed({"key": name, "comp": f"comp_{side}", "parts": f"parts_{side}"})

        def enough(most: Column) -> Column:
            return (100 + self.percent) * most >= self.percent * (F.col("n_x") + F.col("n_y"))

        on = {x: ["middle", *(f"{c}_{x}" for c in shape)] for x in "xy"}
        by_middle = F.least("i_x", "i_y") + F.least(F.col("c_x") - F.col("i_x"), F.col("c_y") - F.col("i_y"))
        by_parts = F.aggregate(F.zip_with("parts_x", "parts_y", lambda x, y: F.least(x, y)), F.lit(0), lambda total, x: total + x)
        sizes = (F.col("n_x") <= F.col("n_y")) & (100 * F.col("n_x") >= self.percent * F.col("n_y"))
        shapes = of("x").distinct().join(of("y").distinct(), "middle").where(sizes & enough(by_middle))
        classes = shapes.join(classes_of("x"), on["x"]).join(classes_of("y"), on["y"]).where((F.col("comp_x") != F.col("comp_y")) & enough(by_parts)).drop("parts_x", "parts_y")
        pairs = classes.join(sets_of("x", "a"), [*on["x"], "comp_x"]).join(sets_of("y", "b"), [*on["y"], "comp_y"]).where(enough(by_parts))
        return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
