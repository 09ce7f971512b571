"""The operators' queries over whole tables, and their SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.llm import chat, decontaminate, htmltext, langid, linededup, neardup, oracles, quality, sharding, tokenize, warc


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_adaptive_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.judge(_table(spark, sf_dir, "documents"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op2_multi_order_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = neardup.JaccardClasses(_table(spark, sf_dir, "documents")).run()
    return found.withColumnRenamed("id", "doc_id")


def op3_wu_manber(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = _table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark")
    return decontaminate.digest(decontaminate.find_contamination(docs, items))


def op4_tag_path_ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return htmltext.extract(pages).withColumn("n_chars", F.char_length("text").cast("long"))


def op5_snapshot_collapse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.render(chat.collapse_snapshots(_table(spark, sf_dir, "conversations")))


def op6_virtual_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_records(_table(spark, sf_dir, "documents"), 16)[0]


def tokenizer_spec(path: str | None = None) -> str:
    """JSON of the tokenizer file; by default the public byte-level one with 50k pieces."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as f:
        return f.read()


def op7_word_table_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = tokenizer_spec()
    coded = tokenize.encode(_table(spark, sf_dir, "documents"), spec, decoded_col="decoded")
    return coded.select(
        "doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
    )


def damaged(pages: DataFrame) -> DataFrame:
    """A replica of the pages in which about one page of 61 has lost its first character."""
    rotten = F.conv(F.substring(F.md5(F.col("url").cast("binary")), 1, 8), 16, 10).cast("long") % 61 == 7
    return pages.withColumn("html", F.when(rotten, F.expr("substring(html, 2)")).otherwise(F.col("html")))


def op8_merkle_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = _table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return warc.audit(pages, damaged(pages))


def held_out() -> Column:
    """A fifth of the documents, by a checksum of the id. A null id is held out."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) == 0, F.lit(True))


def op9_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    model = langid.fit(docs.where(~held_out()))
    return langid.identify(docs, model, keep=["doc_id"]).select(
        "doc_id", held_out().alias("held_out"), F.col("_lang_pred").alias("lang_pred"),
        F.col("_score").alias("score"), F.col("_noise").alias("noise"), F.col("_languages").alias("languages"),
    )


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return linededup.dedup_lines(docs).select(
        "doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"),
        F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"),
    )


QUERIES = {f.__name__: f for f in (op1_adaptive_quality, op2_multi_order_jaccard, op3_wu_manber, op4_tag_path_ratios, op5_snapshot_collapse, op6_virtual_slots, op7_word_table_bpe, op8_merkle_fixity, op9_language_mixture, op10_line_dedup)}

SQL = {
    "op1_adaptive_quality": oracles.OP1,
    "op2_multi_order_jaccard": oracles.OP2,
    "op3_wu_manber": oracles.OP3,
    "op5_snapshot_collapse": """
        WITH t AS (
            SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn, coalesce(role, ''), coalesce(text, '')) AS k,
                   '<|' || coalesce(role, '') || '|>' || chr(10) || coalesce(text, '') || chr(10) || '<|end|>' || chr(10) AS piece
            FROM conversations),
        p AS (SELECT conv_id, k, string_agg(piece, '') OVER (PARTITION BY conv_id ORDER BY k) AS prefix,
                     count(*) OVER (PARTITION BY conv_id) AS n FROM t),
        w AS (SELECT min(conv_id) AS conv_id, n AS n_turns, count(*) AS n_copies, prefix AS text FROM p WHERE k = n GROUP BY n, prefix)
        SELECT conv_id, n_turns, n_copies, text FROM w
        WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.k < p.n AND p.k = w.n_turns AND p.prefix = w.text)
    """,
    "op8_merkle_fixity": """
        WITH n AS (SELECT greatest(1, ceil(count(*) / 1000.0))::BIGINT AS archives FROM pages),
        p AS (SELECT page_id, url, coalesce(html, '') AS body,
                     CASE WHEN ('0x' || substr(md5(url), 1, 8))::BIGINT % 61 = 7 THEN substr(html, 2) ELSE html END AS other,
                     ('0x' || substr(md5(page_id::VARCHAR), 1, 8))::BIGINT % archives AS archive FROM pages, n),
        r AS (SELECT page_id, url, archive,
                     'WARC/1.1' || chr(13) || chr(10) || 'WARC-Type: resource' || chr(13) || chr(10) || 'WARC-Record-ID: <urn:record:' || page_id
                     || '>' || chr(13) || chr(10) || 'WARC-Target-URI: ' || url || chr(13) || chr(10) || 'Content-Type: text/html' || chr(13) || chr(10) || 'Content-Length: ' AS head,
                     body, other, chr(13) || chr(10) || chr(13) || chr(10) AS nl FROM p),
        d AS (SELECT page_id, url, archive, strlen(head || strlen(body) || nl || body || nl) AS n_bytes,
                     sha256(head || strlen(body) || nl || body || nl) AS expected_sha256,
                     sha256(head || strlen(other) || nl || other || nl) AS found_sha256 FROM r),
        o AS (SELECT *, row_number() OVER w - 1 AS pos, (sum(n_bytes) OVER (w ROWS UNBOUNDED PRECEDING) - n_bytes)::BIGINT AS record_offset
              FROM d WINDOW w AS (PARTITION BY archive ORDER BY page_id, url, expected_sha256))
        SELECT page_id, url, archive, pos, record_offset, n_bytes, expected_sha256, found_sha256 FROM o WHERE expected_sha256 <> found_sha256
    """,
    "op10_line_dedup": """
        WITH l AS (
            SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
                   generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos FROM documents),
        k AS (SELECT *, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                     'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
        c AS (SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
        m AS (SELECT k.*, c.key IS NOT NULL AND k.doc_id <> c.keeper AS gone FROM k LEFT JOIN c ON k.key = c.key)
        SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
               sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
        FROM m GROUP BY doc_id
    """,
}
