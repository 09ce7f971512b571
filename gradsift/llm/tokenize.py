"""Byte-level BPE over a distinct-word table, and its inverse.

Texts are split into words in blocks of bounded size: a space and what follows it up to the
next white space, or white space of its own. Byte-level BPE cuts there in any case, so a
word's ids don't depend on its neighbours. Each block sends its distinct words once, packed
by word hash, so a frequent word costs one entry a block and not one an occurrence. A task
of a hash slot merges what the blocks sent, encodes each distinct word once and sends the
ids back to the block; it takes the blocks of 64 input tasks and 32 blocks of each at most, 8 GB
of texts, so its input doesn't grow with the corpus; its texts, packed, meet them there, and each word's place gets the
word's ids. Decoding looks each id up in the id-to-piece table, whose size is the
vocabulary's.

Python's re splits texts of common scripts, where its white space is the tokenizer's; the
tokenizer's own splitter does others.

Defined results: a null text is an empty one and has no ids; rows are independent of each
other, repeated ids too; the text of an added token is that token, as in the library.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from gradsift.llm.memory import trim, trimmed

BLOCK_BYTES = 4 << 20
#: Input tasks, and blocks of each, whose words one task merges.
COHORT = (64, 32)
_TASK = 1_000_000
_WORDS = re.compile(r" ?\S+|\s+(?!\S)|\s+")
_RARE = re.compile("[^\x00-\x1b\x20-ʯ‐-‧₠-₿]")


class Splitter:
    """Texts to words. An added token's text is a word of its own."""

    def __init__(self, spec: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(spec)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        added = sorted((t["content"] for t in json.loads(spec)["added_tokens"]), key=len, reverse=True)
        self.added = re.compile("(" + "|".join(map(re.escape, added)) + ")") if added else None
        self.added_words = frozenset(added)

    def _plain(self, text: str) -> list[str]:
        if _RARE.search(text) is None:
            return _WORDS.findall(text)
        return [text[a:b] for _, (a, b) in self.tokenizer.pre_tokenizer.pre_tokenize_str(text)]

    def words(self, text: str) -> list[str]:
        if self.added is None or self.added.search(text) is None:
            return self._plain(text)
        out: list[str] = []
        for part in self.added.split(text):
            if part in self.added_words:
                out.append(part)
            elif part:
                out += self._plain(part)
        return out

    def encode(self, words: list[str]) -> list[list[int]]:
        out: list[list[int]] = []
        for at in range(0, len(words), 4096):
            out += [e.ids for e in self.tokenizer.encode_batch(words[at : at + 4096], add_special_tokens=False)]
        return out


@lru_cache(maxsize=2)
def _splitter(spec: str) -> Splitter:
    return Splitter(spec)


def _pack(*parts: np.ndarray | bytes, level: int = 3) -> bytes:
    raw = [p if isinstance(p, bytes) else np.ascontiguousarray(p).tobytes() for p in parts]
    head = np.array([len(raw), *map(len, raw)], dtype="<i8").tobytes()
    return zstandard.ZstdCompressor(level=level).compress(head + b"".join(raw))


def _planes(x: np.ndarray) -> bytes:
    """Numbers below 2**32 as their four bytes' planes, most of which are then alike."""
    return np.ascontiguousarray(x.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes()


def _from_planes(raw: memoryview) -> np.ndarray:
    planes = np.frombuffer(raw, np.uint8).reshape(4, -1)
    return np.ascontiguousarray(planes.T).view("<u4").ravel()


def _unpack(blob: bytes) -> list[memoryview]:
    data = memoryview(zstandard.ZstdDecompressor().decompress(blob))
    n = int(np.frombuffer(data[:8], "<i8")[0])
    sizes = np.frombuffer(data[8 : 8 * (n + 1)], "<i8").tolist()
    out, at = [], 8 * (n + 1)
    for size in sizes:
        out.append(data[at : at + size])
        at += size
    return out


def _pack_words(words: list[str]) -> tuple[bytes, bytes]:
    raw = [w.encode() for w in words]
    return _planes(np.array([*map(len, raw)], dtype="<u4")), b"".join(raw)


def _read_words(lengths: memoryview, raw: memoryview) -> list[str]:
    ends = np.cumsum(_from_planes(lengths), dtype=np.int64).tolist()
    data, at, out = bytes(raw), 0, []
    for to in ends:
        out.append(data[at:to].decode())
        at = to
    return out


def _by_slot(words: Iterable[str], slots: int) -> list[list[str]]:
    out: list[list[str]] = [[] for _ in range(slots)]
    for w in sorted(words):
        out[zlib.crc32(w.encode()) % slots].append(w)
    return out


def _checksum(words: list[str]) -> int:
    return zlib.crc32("\0".join(words).encode()) + (len(words) << 32)


def _ragged(values: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """values[starts[i] : starts[i] + lengths[i]] for all i, one after the other."""
    total = int(lengths.sum())
    if not total:
        return values[:0]
    at = np.repeat(starts - (np.cumsum(lengths) - lengths), lengths) + np.arange(total)
    return values[at]


def _blocks(batches: Iterator[pa.RecordBatch], block_bytes: int) -> Iterator[tuple[int, list, list[str]]]:
    """Block number, ids and texts. The number is the task's partition and a count."""
    part, k, ids, texts, size = TaskContext.get().partitionId(), 0, [], [], 0
    for batch in batches:
        own_ids = batch.column(0)
        for i, text in enumerate(batch.column(1)):
            text = text.as_py() or ""
            ids.append(own_ids[i].as_py())
            texts.append(text)
            size += len(text) + 64
            if size >= block_bytes:
                yield part * _TASK + k, ids, texts
                k, ids, texts, size = k + 1, [], [], 0
    if ids:
        yield part * _TASK + k, ids, texts


def cohort_of(block: int, tasks: int, blocks: int) -> int:
    """A number for the blocks whose words meet; each has tasks * blocks of them at most."""
    return block // _TASK // tasks * _TASK + block % _TASK // blocks


def encode(docs: DataFrame, spec: str, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES, n_slots: int | None = None, decoded_col: str | None = None, cohort: tuple[int, int] = COHORT) -> DataFrame:
    """(id, ids): ids are little-endian unsigned 32-bit integers. spec: the tokenizer's JSON.

    With decoded_col, also the text of the ids, as decode gives it, by the same worker.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(spec)
    pieces = spark.sparkContext.broadcast(piece_table(spec)) if decoded_col else None
    slots = n_slots or 2 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    source = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_text"))
    id_type = source.schema["_id"].dataType.simpleString()
    id_arrow = to_arrow_type(source.schema["_id"].dataType)
    exchange = pa.schema([("_slot", pa.int32()), ("_cohort", pa.int64()), ("_block", pa.int64()), ("_words", pa.binary())])
    answer = pa.schema([("_block", pa.int64()), ("_blob", pa.binary())])

    def distinct_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        split = _splitter(shared.value).words
        for block, _, texts in _blocks(batches, block_bytes):
            found: set[str] = set()
            for text in texts:
                found.update(split(text))
            rows = [(s, cohort_of(block, *cohort), block, _pack(*_pack_words(ws))) for s, ws in enumerate(_by_slot(found, slots)) if ws]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), exchange, strict=True)] if rows else [pa.array([], f.type) for f in exchange], schema=exchange)

    def encode_slot(group: pa.Table) -> pa.Table:
        out = encode_words(group)
        trim()
        return out

    def encode_words(group: pa.Table) -> pa.Table:
        asked = [_read_words(*_unpack(b)) for b in group.column("_words").to_pylist()]
        every = sorted(set().union(*asked))
        ids = dict(zip(every, _splitter(shared.value).encode(every), strict=True))
        blobs = []
        for ws in asked:
            own = [ids[w] for w in ws]
            flat = np.array([i for x in own for i in x], dtype="<u4")
            lengths = np.array([*map(len, own)], dtype="<u4")
            slot = group.column("_slot")[0].as_py()
            blobs.append(_pack(np.array([slot, _checksum(ws)], dtype="<u8"), _planes(lengths), _planes(flat)))
        return pa.table([group.column("_block"), pa.array(blobs, pa.binary())], schema=answer)

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block, ids, texts in _blocks(batches, block_bytes):
            blob = _pack(_ids_blob(ids, id_arrow), *_pack_words(texts), level=6)
            yield pa.RecordBatch.from_arrays([pa.array([block], pa.int64()), pa.array([blob], pa.binary())], schema=answer)

    def assemble(answered: pa.Table, block: pa.Table) -> pa.Table:
        out = put_together(answered, block)
        trim()
        return out

    def put_together(answered: pa.Table, block: pa.Table) -> pa.Table:
        sent = {}
        for blob in answered.column("_blob").to_pylist():
            head, lengths, ids = _unpack(blob)
            slot, check = np.frombuffer(head, "<u8").tolist()
            sent[slot] = check, _from_planes(lengths).astype(np.int64), _from_planes(ids)
        out_ids, out = [pa.array([], id_arrow)], []
        split = _splitter(shared.value).words
        for blob in block.column("_blob").to_pylist():
            keys, sizes, raw = _unpack(blob)
            place: dict[str, int] = {}
            where = [np.array([place.setdefault(w, len(place)) for w in split(text)], dtype="<u4") for text in _read_words(sizes, raw)]
            begin, size = np.zeros((2, len(place)), dtype=np.int64)
            parts, at = [np.zeros(0, dtype="<u4")], 0
            for slot, own in enumerate(_by_slot(place, slots)):
                if not own:
                    continue
                check, lengths, ids = sent.get(slot, (None, None, None))
                if check != _checksum(own):
                    # the block was cut otherwise when it was read again: its words are encoded here
                    found = _splitter(shared.value).encode(own)
                    lengths, ids = np.array([*map(len, found)]), np.array([i for x in found for i in x], dtype="<u4")
                to = np.array([place[w] for w in own])
                begin[to] = at + np.cumsum(lengths) - lengths
                size[to] = lengths
                parts.append(ids)
                at += len(ids)
            values = np.concatenate(parts)
            out_ids.append(_read_ids(keys))
            out += [_ragged(values, begin[own], size[own]).astype("<u4").tobytes() for own in where]
        made = [pa.concat_arrays(out_ids), pa.array(out, pa.binary())]
        if pieces is None:
            return pa.table(made, names=["_id", "ids"])
        join = PieceJoin(pieces.value)
        return pa.table([*made, pa.array(map(join.text, out), pa.string())], names=["_id", "ids", decoded_col])

    answers = (
        source.mapInArrow(trimmed(distinct_words), "_slot int, _cohort long, _block long, _words binary")
        .groupBy("_slot", "_cohort").applyInArrow(encode_slot, "_block long, _blob binary")
    )
    placed = source.mapInArrow(trimmed(packed), "_block long, _blob binary")
    # two exchanges, not a union: a task of a union has another partition number, and so block
    return (
        answers.groupBy("_block").cogroup(placed.groupBy("_block"))
        .applyInArrow(assemble, f"_id {id_type}, ids binary" + (f", `{decoded_col}` string" if decoded_col else ""))
        .withColumnRenamed("_id", id_col)
    )


def _ids_blob(ids: list, kind: pa.DataType) -> bytes:
    sink = pa.BufferOutputStream()
    batch = pa.RecordBatch.from_arrays([pa.array(ids, kind)], names=["id"])
    with pa.ipc.new_stream(sink, batch.schema) as writer:
        writer.write_batch(batch)
    return sink.getvalue().to_pybytes()


def _read_ids(blob: memoryview) -> pa.Array:
    return pa.ipc.open_stream(pa.py_buffer(blob)).read_all().column(0).combine_chunks()


def piece_table(spec: str) -> list[bytes]:
    """Bytes of each id. Byte-level pieces spell each byte as a printable character."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    back = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}
    parts = json.loads(spec)
    vocab = parts["model"]["vocab"] | {t["content"]: t["id"] for t in parts["added_tokens"]}
    out = [b""] * (max(vocab.values()) + 1)
    for piece, i in vocab.items():
        out[i] = b"".join(bytes([back[c]]) if c in back else c.encode() for c in piece)
    return out


class PieceJoin:
    """The id-to-piece table, laid out for looking up many ids at once."""

    def __init__(self, pieces: list[bytes]):
        self.raw = np.frombuffer(b"".join(pieces), dtype=np.uint8)
        self.lengths = np.array([*map(len, pieces)], dtype=np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths

    def text(self, blob: bytes | None) -> str:
        ids = np.frombuffer(blob or b"", "<u4")
        return _ragged(self.raw, self.starts[ids], self.lengths[ids]).tobytes().decode("utf-8", "replace")


def decode(encoded: DataFrame, spec: str, ids_col: str = "ids", text_col: str = "decoded") -> DataFrame:
    """Adds the text of the ids; bytes that are not UTF-8 become U+FFFD. Null ids are none."""
    shared = encoded.sparkSession.sparkContext.broadcast(piece_table(spec))
    at = encoded.columns.index(ids_col)

    def texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        join = PieceJoin(shared.value)
        for batch in batches:
            out = [join.text(blob.as_py()) for blob in batch.column(at)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.string())], names=[*batch.schema.names, text_col])

    kind = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in encoded.schema)
    return encoded.mapInArrow(trimmed(texts), f"{kind}, `{text_col}` string")
