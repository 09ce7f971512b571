"""Shards by fixed virtual slots.

A record's slot is a hash of its id, and never changes. Bytes are summed per slot, and a
small versioned table, kept beside the shards, maps slots to shards. Version 1 deals the
slots out in turn; a later version is an edit of the one before, made to even out the
shards' bytes or to take in another shard. Only the moved slots' records move. A stored
version is never written again.

Defined results: a null text has no bytes; a null id is an id of its own; rows that repeat
an id share a slot; an empty table has no rows and an unedited map.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.llm.staging import shared_dir

N_SLOTS = 4096


def slot_of(id_col: str, n_slots: int = N_SLOTS) -> Column:
    return F.pmod(F.xxhash64(F.col(id_col)), F.lit(n_slots)).cast("int")


def record_bytes(text_col: str) -> Column:
    """UTF-8 bytes, and one for the record's end."""
    return (F.coalesce(F.octet_length(F.col(text_col)), F.lit(0)) + F.lit(1)).cast("long")


@dataclass
class SlotMap:
    """slot -> shard, by version. Its size is the number of slots, whatever the data."""

    n_shards: int
    n_slots: int = N_SLOTS
    versions: list[np.ndarray] = field(default_factory=list)

    def __post_init__(self) -> None:
        if self.n_shards < 1 or self.n_slots < self.n_shards:
            raise ValueError("as many slots as shards are needed, and one shard")
        if not self.versions:
            self.versions.append(np.arange(self.n_slots) % self.n_shards)

    @property
    def current(self) -> np.ndarray:
        return self.versions[-1]

    def loads(self, slot_bytes: np.ndarray) -> np.ndarray:
        return np.bincount(self.current, weights=slot_bytes, minlength=self.n_shards)

    def rebalance(self, slot_bytes: np.ndarray, max_edits: int = 20_000) -> int:
        """A new version in which no move or swap from the fullest shard to the emptiest helps.

        Returns the number of slots that changed their shard.
        """
        shard, size = self.current.copy(), slot_bytes.astype(np.int64)
        load = np.bincount(shard, weights=size, minlength=self.n_shards).astype(np.int64)
        for _ in range(max_edits):
            hi, lo = int(load.argmax()), int(load.argmin())
            gap = int(load[hi] - load[lo])
            own, other = np.flatnonzero(shard == hi), np.flatnonzero(shard == lo)
            other = other[np.argsort(size[other], kind="stable")]
            # what a single slot, or a slot against one of the other shard, would carry over
            best, choice = gap, None
            if len(own):
                k = int(np.abs(2 * size[own] - gap).argmin())
                best, choice = abs(gap - 2 * int(size[own[k]])), (own[k], None)
            if len(own) and len(other):
                near = np.searchsorted(size[other], size[own] - gap // 2)
                for shift in (-1, 0):
                    j = np.clip(near + shift, 0, len(other) - 1)
                    left = np.abs(gap - 2 * (size[own] - size[other[j]]))
                    k = int(left.argmin())
                    if left[k] < best:
                        best, choice = int(left[k]), (own[k], other[j[k]])
            if choice is None or best >= gap:
                break
            a, b = choice
            carried = int(size[a]) - (int(size[b]) if b is not None else 0)
            shard[a] = lo
            if b is not None:
                shard[b] = hi
            load[hi] -= carried
            load[lo] += carried
        moved = int((shard != self.current).sum())
        self.versions.append(shard)
        return moved

    def grow(self, slot_bytes: np.ndarray) -> int:
        """A new version with one more shard, which takes slots from the others and gives none."""
        shard, size = self.current.copy(), slot_bytes.astype(np.int64)
        new, self.n_shards = self.n_shards, self.n_shards + 1
        share = size.sum() / self.n_shards
        load = np.bincount(shard, weights=size, minlength=self.n_shards)
        for old in range(new):
            over = load[old] - share
            for s in np.flatnonzero(shard == old)[np.argsort(-size[shard == old], kind="stable")]:
                if 0 < size[s] <= over:
                    shard[s] = new
                    over -= size[s]
        moved = int((shard != self.current).sum())
        self.versions.append(shard)
        return moved

    def frame(self, spark: SparkSession, first: int = 1) -> DataFrame:
        """(version, slot, shard) of the versions from the first on."""
        rows = [(v, s, int(x)) for v, m in enumerate(self.versions, 1) if v >= first for s, x in enumerate(m)]
        return spark.createDataFrame(rows, "version int, slot int, shard int")

    def store(self, spark: SparkSession, path: str) -> None:
        """Writes the versions that the path doesn't have, each to a folder of its own."""
        for v in range(_stored(spark, path) + 1, len(self.versions) + 1):
            self.frame(spark, v).where(F.col("version") == v).drop("version").coalesce(1).write.mode("error").parquet(f"{path}/version={v}")

    @staticmethod
    def load(spark: SparkSession, path: str) -> SlotMap:
        """The map as stored, with all its versions."""
        last = _stored(spark, path)
        if not last:
            raise FileNotFoundError(f"no slot map in {path}")
        versions = []
        for v in range(1, last + 1):
            rows = spark.read.parquet(f"{path}/version={v}").toPandas().sort_values("slot")
            if rows["slot"].tolist() != list(range(len(rows))):
                raise ValueError(f"version {v} of the slot map has not every slot once")
            versions.append(rows["shard"].to_numpy(dtype=np.int64))
        return SlotMap(int(versions[-1].max()) + 1, len(versions[-1]), versions)


def _stored(spark: SparkSession, path: str) -> int:
    """The number of finished versions in a path."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs, last = at.getFileSystem(spark._jsc.hadoopConfiguration()), 0
    while fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{path}/version={last + 1}/_SUCCESS")):
        last += 1
    return last


#: Rows of a part of a slot, which one task orders.
PART_ROWS = 1_000_000


def slot_totals(docs: DataFrame, id_col: str, text_col: str, n_slots: int = N_SLOTS, parts: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of each slot, and rows of each slot's parts; n_slots * parts rows reach the driver."""
    size, rows = np.zeros(n_slots, dtype=np.int64), np.zeros((n_slots, parts), dtype=np.int64)
    found = (
        docs.select(slot_of(id_col, n_slots).alias("s"), _part_of(id_col, text_col, parts).alias("p"), record_bytes(text_col).alias("b"))
        .groupBy("s", "p").agg(F.sum("b").alias("b"), F.count(F.lit(1)).alias("n"))
    )
    for r in found.collect():
        size[r["s"]] += r["b"]
        rows[r["s"], r["p"]] = r["n"]
    return size, rows


def _checksum(text_col: str) -> Column:
    return F.crc32(F.coalesce(F.col(text_col), F.lit("")).cast("binary"))


def _part_of(id_col: str, text_col: str, parts: int) -> Column:
    """Of a slot, by id and text, so that rows that repeat an id don't all meet."""
    return F.lit(0) if parts == 1 else F.pmod(F.xxhash64(F.lit("part"), F.col(id_col), _checksum(text_col)), F.lit(parts)).cast("int")


def shard_records(docs: DataFrame, n_shards: int, id_col: str = "doc_id", text_col: str = "text", n_slots: int = N_SLOTS, map_path: str | None = None, part_rows: int = PART_ROWS) -> tuple[DataFrame, SlotMap]:
    """Each record's size, checksum, virtual slot, shard and place in its shard; and the map.

    The map is the one stored in map_path, or a new one of n_shards; it is rebalanced by an
    edit, stored as the next version, and read back for the join. A place is the rank within
    a part of the virtual slot plus the rows of the shard's earlier slots and parts, so the
    places of a shard run from 0 without a gap, and a task orders about part_rows rows.
    """
    spark = docs.sparkSession
    map_path = map_path or f"{shared_dir(spark)}/slot-map-{uuid.uuid4().hex}"
    placed = SlotMap.load(spark, map_path) if _stored(spark, map_path) else SlotMap(n_shards, n_slots)
    if placed.n_shards > n_shards:
        raise ValueError(f"the stored map has {placed.n_shards} shards")
    n_slots = placed.n_slots
    parts = max(1, -(-docs.count() // (n_slots * part_rows)))
    size, rows = slot_totals(docs, id_col, text_col, n_slots, parts)
    while placed.n_shards < n_shards:
        placed.grow(size)
    placed.rebalance(size)
    placed.store(spark, map_path)
    placed = SlotMap.load(spark, map_path)
    shard, first = placed.current, np.zeros((n_slots, parts), dtype=np.int64)
    for s in range(placed.n_shards):
        own = shard == s
        upto = np.cumsum(rows[own])
        first[own] = (upto - rows[own].ravel()).reshape(-1, parts)
    table = spark.createDataFrame(
        [(i, p, int(shard[i]), int(first[i, p])) for i in range(n_slots) for p in range(parts)], "_vs int, _part int, shard int, _first long"
    )
    records = docs.select(
        F.col(id_col).alias("doc_id"), record_bytes(text_col).alias("size"), _checksum(text_col).alias("text_crc32"),
        slot_of(id_col, n_slots).alias("_vs"), _part_of(id_col, text_col, parts).alias("_part"),
    )
    order = Window.partitionBy("_vs", "_part").orderBy("doc_id", "text_crc32", "size")
    out = (
        records.withColumn("_rank", F.row_number().over(order) - 1)
        .join(F.broadcast(table), ["_vs", "_part"])
        .select(
            "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard",
            (F.col("_first") + F.col("_rank")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
            F.col("_vs").alias("virtual_slot"), F.lit(len(placed.versions)).alias("map_version"),
        )
    )
    return out, placed
