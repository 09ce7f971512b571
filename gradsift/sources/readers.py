"""Readers of other formats: JSON lines, CSV, text, and binary image files."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CAPTIONS = "sample_id long, caption string"


def read_captions(spark: SparkSession, path: str, form: str = "json", schema: str = CAPTIONS) -> DataFrame:
    """json, csv (with a header) or parquet, by a declared schema."""
    reader = spark.read.schema(schema)
    return (reader.option("header", True).option("multiLine", True).option("escape", '"') if form == "csv" else reader).format(form).load(path)


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """A text file's lines as captions; the id is a hash of file and place."""
    lines = spark.read.text(path).select(F.col("value").alias("caption"), F.col("_metadata.file_path").alias("_f"))
    return lines.withColumn("sample_id", F.xxhash64("_f", "caption")).select("sample_id", "caption")


def decode_pgm(raw: bytes) -> tuple[int, int, np.ndarray]:
    """Height, width and cells in [0, 1] of a binary grey map."""
    head, at = [], 0
    while len(head) < 4:
        while raw[at : at + 1].isspace():
            at += 1
        if raw[at : at + 1] == b"#":
            at = raw.index(b"\n", at)
            continue
        to = at
        while not raw[to : to + 1].isspace():
            to += 1
        head.append(raw[at:to])
        at = to
    if head[0] != b"P5":
        raise ValueError("not a binary grey map")
    w, h, top = map(int, head[1:])
    cells = np.frombuffer(raw, dtype=np.uint8 if top < 256 else ">u2", count=w * h, offset=at + 1)
    return h, w, cells / top


def read_images(spark: SparkSession, path: str, side: int = 8) -> DataFrame:
    """Image files as side x side mean pools: path, height, width, pixels.

    Files are decoded where they are read; only the pools go on.
    """
    schema = pa.schema([("path", pa.string()), ("height", pa.int32()), ("width", pa.int32()), ("pixels", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for p, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                h, w, cells = decode_pgm(raw)
                r, c = np.arange(h) * side // h, np.arange(w) * side // w
                at = (r[:, None] * side + c).ravel()
                total, n = np.bincount(at, cells, side * side), np.bincount(at, minlength=side * side)
                rows.append((p, h, w, (total / np.maximum(n, 1)).tolist()))
            yield pa.RecordBatch.from_arrays([pa.array(col, f.type) for col, f in zip(zip(*rows), schema, strict=True)] if rows else [pa.array([], f.type) for f in schema], schema=schema)

    files = spark.read.format("binaryFile").load(path).select("path", "content")
    return files.mapInArrow(run, "path string, height int, width int, pixels array<double>")
