"""Readers, batching, splits and corpora."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from gradsift.functions.features import bigram_profile, class_table, standardise_by_corpus
from gradsift.operators.batching import assign_batches, hash_sample, without_copies
from gradsift.sources import corpora, readers
from gradsift.sources.staging import staged


def test_formats_round_trip(spark, tmp_path):
    rows = [(1, 'a "quoted", line\nand more'), (2, "é")]
    df = spark.createDataFrame(rows, readers.CAPTIONS)
    for form in ("json", "csv", "parquet"):
        path = str(tmp_path / form)
        writer = df.write.option("header", True).option("escape", '"') if form == "csv" else df.write
        writer.format(form).save(path)
        assert sorted(map(tuple, readers.read_captions(spark, path, form).collect())) == rows


def test_lines(spark, tmp_path):
    (tmp_path / "t.txt").write_text("one\ntwo\n")
    assert {r.caption for r in readers.read_lines(spark, str(tmp_path / "t.txt")).collect()} == {"one", "two"}


def test_images_are_pooled(spark, tmp_path):
    cells = np.zeros((16, 24), dtype=np.uint8)
    cells[:2, :3] = 255
    (tmp_path / "a.pgm").write_bytes(b"P5\n# made here\n24 16\n255\n" + cells.tobytes())
    r = readers.read_images(spark, str(tmp_path)).first()
    assert (r.height, r.width, len(r.pixels)) == (16, 24, 64)
    assert r.pixels[0] == pytest.approx(1) and sum(r.pixels[1:]) == 0
    with pytest.raises(ValueError):
        readers.decode_pgm(b"P6\n1 1\n255\nabc")


def test_exact_batches(spark):
    sizes = [r["count"] for r in assign_batches(spark.range(130), "id", 64, how="exact").groupBy("batch_id").count().orderBy("batch_id").collect()]
    assert sizes == [64, 64, 2]
    a, b = (assign_batches(spark.range(130), "id", 64, epoch=e).orderBy("id").collect() for e in (0, 1))
    assert a != b
    with pytest.raises(ValueError):
        assign_batches(spark.range(3), "id", how="other")


def test_hash_sample_is_repeatable(spark):
    one, two = (sorted(r.id for r in hash_sample(spark.range(5000).repartition(p), "id", 0.2, 3).collect()) for p in (1, 7))
    assert one == two and 850 < len(one) < 1150


def test_copies_of_held_out_texts_leave_the_pool(spark):
    train = spark.createDataFrame([(1, "a"), (2, "b"), (3, None)], "id long, text string")
    held = spark.createDataFrame([(9, "a")], "id long, text string")
    assert {r.id for r in without_copies(train, held).collect()} == {2, 3}
    sf = "/root/testdata/sf0.001"
    val = {r.text for r in corpora.wanted(spark, sf).collect()}
    assert val and not val & {r.text for r in corpora.train_pool(spark, sf).collect()}


def test_classes_and_profiles():
    assert class_table(8)[[ord("a"), ord("b"), ord("B"), 128, ord("7"), 32, 10, ord("#")]].tolist() == list(range(8))
    assert class_table(128)[65] == 65
    with pytest.raises(ValueError):
        class_table(9)
    cells, counts = bigram_profile("abab", 32)
    assert dict(zip(cells.tolist(), counts.tolist(), strict=True)) == {1: 2, 32: 1}
    assert bigram_profile(None, 32)[0].size == 0 == bigram_profile("x", 32)[0].size


def test_standardised_features(spark):
    df = spark.createDataFrame([([1.0, 5.0],), ([3.0, 5.0],)], "features array<double>")
    out = sorted(r.features for r in standardise_by_corpus(df, "features", 2).collect())
    assert out == [[-1.0, 0.0], [1.0, 0.0]]


def test_staged_tables_are_read_back(spark):
    df = staged(spark.range(10).withColumn("x", F.rand(1)))
    assert df.collect() == df.collect() and df.count() == 10
