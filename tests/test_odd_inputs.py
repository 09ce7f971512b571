"""Queries on small tables with odd rows, against their SQL."""

from __future__ import annotations

import math

import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from gradsift.catalog import QUERIES, SQL
from tests.helpers import assert_equal, database


@pytest.mark.parametrize(("texts", "vector", "defined"), [
    (["abİz", "a İİ"], [1.0, 0.0], True),
    (["abc", "À 1."], [1.0, 0.0], False),
    (["abc", ""], [1.0, 0.0], False),
    (["abc", "cab"], [0.0, 0.0], False),
])
def test_alignment_without_letters_or_pixels(spark, tmp_path, texts, vector, defined):
    pq.write_table(pa.table({"doc_id": [0, 1], "text": texts}), tmp_path / "documents.parquet")
    pixels = pa.array([[1.0, 2.0] * 32, vector * 32], pa.list_(pa.float32()))
    pq.write_table(pa.table({"vec_id": [0, 1], "embedding": pixels, "label": pa.array([0, 0], pa.int32())}), tmp_path / "embeddings.parquet")
    found = QUERIES["alignment_score"](spark, str(tmp_path)).first()
    mean, pairs = database(str(tmp_path)).execute(SQL["alignment_score"]).fetchone()
    assert found.pairs == pairs == 2
    assert found.alignment == pytest.approx(mean, abs=1e-9, nan_ok=True) and math.isfinite(mean) == defined


def test_schedules_follow_the_documents(spark, tmp_path):
    sizes = [None, 0, 1, 512, 513, 2_000_000]
    pq.write_table(pa.table({"doc_id": range(6), "n_chars": pa.array(sizes, pa.int64())}), tmp_path / "documents.parquet")
    df = QUERIES["udtf_unroll_steps"](spark, str(tmp_path))
    assert len(df.inputFiles()) == 1
    assert {r.doc_id: r["count"] for r in df.groupBy("doc_id").count().collect()} == {2: 1, 3: 1, 4: 2, 5: 3907}
    assert_equal(spark, QUERIES["udtf_unroll_steps"], SQL["udtf_unroll_steps"], str(tmp_path))
