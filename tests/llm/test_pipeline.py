"""The pipeline's stages against plain versions on a small corpus."""

from __future__ import annotations

import corpus_pipeline as pipeline
from tests.llm.fixtures import documents, frame
from tests.llm.test_operators import brute_classes

SF = "/root/testdata/sf0.001"


def test_stage_columns_and_edges(spark):
    docs = frame(spark)
    assert [n for n, _ in pipeline.STAGES] == ["language_id", "line_dedup", "ngram_jaccard", "decontamination", "bpe"]
    for _, step in pipeline.STAGES[:-1]:
        out = step(spark, docs, SF)
        assert out.columns == docs.columns
        assert step(spark, docs.limit(0), SF).count() == 0
    assert pipeline.STAGES[-1][1](spark, docs.limit(0), SF).count() == 0


def test_language_stage_rejects_only_what_has_no_letters(spark):
    rows = documents()
    kept = [r.doc_id for r in pipeline.language_id(spark, frame(spark, rows), SF).collect()]
    no_letters = {i for i, t, *_ in rows if not any(c.isalpha() for c in t or "")}
    assert not no_letters & set(kept)
    assert set(range(60)) <= set(kept)


def test_one_document_of_each_class_stays(spark):
    rows = documents()
    kept = sorted(r.doc_id for r in pipeline.ngram_jaccard(spark, frame(spark, rows), SF).collect())
    want = brute_classes(rows)
    assert kept == sorted({c for _, c in want.values()})


def test_rows_that_repeat_an_id_are_told_apart_by_text(spark):
    a, b = "one text of a number of words that is its own and no other's here", "quite another text with a set of words that nobody else has in this table"
    rows = [(3, b, "en", "s", 9, "", 1), (5, a, "en", "s", 9, "", 1), (5, b, "en", "s", 9, "", 1), (5, a, "en", "r", 9, "", 1), (7, " ", "en", "s", 9, "", 1), (7, " ", "en", "s", 9, "", 1)]
    for order in (rows, rows[::-1]):
        kept = pipeline.ngram_jaccard(spark, frame(spark, order, 2), SF).collect()
        assert sorted((r.doc_id, r.text, r.source) for r in kept) == sorted([(3, b, "s"), (5, a, "r"), (7, " ", "s"), (7, " ", "s")])


def test_line_stage_equals_a_plain_version(spark):
    from collections import Counter, defaultdict

    from tests.llm.test_operators import lower

    rows = documents()
    rows.append((rows[5][0], rows[10][1], "en", "s", 1, "", 1))
    holders = defaultdict(set)

    def key(line):
        return lower(line.strip(" \t\n\x0b\x0c\r"))

    for i, text, *_ in rows:
        for line in (text or "").split("\n"):
            holders[key(line)].add(i)
    want = Counter()
    for i, text, lang, source, n, *_ in rows:
        lines = (text or "").split("\n")
        kept = [x for x in lines if not (len(key(x)) >= 40 and len(holders[key(x)]) >= 5 and i != max(holders[key(x)]))]
        want[i, "\n".join(kept), lang, source, len("\n".join(kept)) if len(kept) < len(lines) else n] += 1
    got = pipeline.line_dedup(spark, frame(spark, rows), SF).collect()
    assert Counter((r.doc_id, r.text or "", r.lang, r.source, r.n_chars) for r in got) == want


def test_bpe_stage_equals_the_library(spark):
    import hashlib
    from collections import Counter

    import numpy as np
    from tokenizers import Tokenizer

    from gradsift.llm.queries import tokenizer_spec

    library, rows, want = Tokenizer.from_str(tokenizer_spec()), documents(), Counter()
    for i, text, *_ in rows:
        ids = library.encode(text or "", add_special_tokens=False).ids
        decoded = library.decode(ids, skip_special_tokens=False)
        want[i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest()] += 1
    got = pipeline.bpe(spark, frame(spark, rows), SF).collect()
    assert Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in got) == want


def test_contaminated_documents_go(spark):
    item = spark.read.parquet(f"{SF}/benchmark.parquet").first().text
    rows = [(1, item, "en", "s", 1, "", 1), (2, "clean words of another kind " * 9, "en", "s", 1, "", 1), (1, "same id, other text", "en", "s", 1, "", 1)]
    kept = pipeline.decontamination(spark, frame(spark, rows), SF).collect()
    assert sorted((r.doc_id, r.text[:5]) for r in kept) == [(1, "same "), (2, "clean")]


def test_whole_run(spark):
    out = pipeline.run(spark, SF).collect()
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert 100 < len(out) < docs.count() and len({r.doc_id for r in out}) == len(out)
    assert all(len(r.ids) == 4 * r.n_tokens for r in out)
