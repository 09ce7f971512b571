"""Documents to tokens: language, common lines, near copies, benchmark passages, BPE.

Each stage takes (spark, docs, sf_dir), works on all rows of docs and, but for the last,
returns the columns of documents. Rows that repeat an id are rows of their own; null texts
have no letters and go in the first stage.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.llm import decontaminate, langid, linededup, neardup, queries, tokenize
from gradsift.llm.columns import give_back, hide
from gradsift.llm.staging import Stage

Step = Callable[[SparkSession, DataFrame, str], DataFrame]
#: The stages hash texts, fit a classifier and tokenize, which SQL doesn't express.
ORACLE_SQL = None


def own_columns(step: Step) -> Step:
    """Other columns than those of documents pass through, whatever their names."""

    @wraps(step)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        hidden, back = hide(docs, ("doc_id", "text", "lang", "source", "n_chars"))
        return give_back(step(spark, hidden, sf_dir), back)

    return run


@own_columns
def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts without a letter, and those that are noise more than any language."""
    model = langid.fit(docs)
    if not model.languages:
        return docs.where(F.coalesce("text", F.lit("")).rlike(r"\p{L}"))
    named = langid.identify(docs, model)
    return named.where((F.col("_lang_pred") != "und") & (F.col("_noise") <= 0.5)).select(*(f"`{c}`" for c in docs.columns))


@own_columns
def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops common lines; n_chars follows where a text has changed."""
    out = linededup.dedup_lines(docs)
    n_chars = F.when(F.col("_n_dropped") > 0, F.char_length("text")).otherwise(F.col("n_chars"))
    return out.withColumn("n_chars", n_chars.cast(docs.schema["n_chars"].dataType)).select(*(f"`{c}`" for c in docs.columns))


@own_columns
def ngram_jaccard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near copies, the row with the smallest id stays.

    Rows are told apart by id and text; of rows equal in both, the one whose other columns
    come first as JSON stays. Texts without words are in no class, and all stay.
    """
    row = {"_row_id": F.col("doc_id"), "_row_a": F.xxhash64("text"), "_row_b": F.xxhash64(F.lit("row"), F.col("text"))}
    marked = docs.withColumns(row)
    classes = neardup.JaccardClasses(marked.select(F.struct(*row).alias("row"), "text"), id_col="row").run()
    stays = classes.where(F.col("id").eqNullSafe(F.col("component_id"))).select(*(F.col(f"id.{c}").alias(f"_of{c}") for c in row), F.col("n_shingles").alias("_n")).distinct()
    same = marked["_row_id"].eqNullSafe(stays["_of_row_id"]) & (marked["_row_a"] == stays["_of_row_a"]) & (marked["_row_b"] == stays["_of_row_b"])
    others = F.to_json(F.struct(*(F.col(f"`{c}`") for c in docs.columns if c not in ("doc_id", "text"))))
    once = Window.partitionBy(*row).orderBy(others)
    kept = marked.join(stays, same).withColumn("_nth", F.row_number().over(once))
    return kept.where("_nth = 1 OR _n = 0").select(*(f"`{c}`" for c in docs.columns))


@own_columns
def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops contaminated documents."""
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    marked = docs.withColumn("_text_key", F.xxhash64("text"))
    found = decontaminate.find_contamination(marked, items, keep=["doc_id", "_text_key"])
    gone = decontaminate.digest(found, keep=["doc_id", "_text_key"]).where("contaminated").select(F.col("doc_id").alias("_gone"), F.col("_text_key").alias("_gone_key")).distinct()
    return marked.join(gone, marked["doc_id"].eqNullSafe(gone["_gone"]) & (marked["_text_key"] == gone["_gone_key"]), "left_anti").drop("_text_key")


def bpe(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, and digests of them and of what they decode to."""
    spec = queries.tokenizer_spec()
    coded = tokenize.encode(docs, spec, decoded_col="decoded")
    return coded.select(
        "doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), "ids",
        F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
    )


STAGES = [
    ("language_id", language_id),
    ("line_dedup", line_dedup),
    ("ngram_jaccard", ngram_jaccard),
    ("decontamination", decontamination),
    ("bpe", bpe),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    stage, docs = Stage(spark, "pipeline"), spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES:
        out = step(spark, docs, sf_dir)
        docs = out if name == STAGES[-1][0] else stage.put(out)
    return docs
