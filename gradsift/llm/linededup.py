"""Lines that many documents share, dropped from all but one of them.

Normalised lines are exploded, hashed to 128 bits and counted by document; those at or over
the threshold go from every document but the largest id that has them. The rest of a
document's lines are joined again in their order.

Defined results: a null or empty text is one empty line; rows that repeat an id are one
document in the count; a null id is an id; no line of an empty table is counted. Other
columns stay as they are, whatever their names.
"""

from __future__ import annotations

from string import ascii_lowercase, ascii_uppercase

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradsift.llm.columns import give_back, hide

BLANKS = " \t\n\x0b\x0c\r"


def _lower_ascii(s: Column) -> Column:
    """A-Z only; the cheaper lower() does the same where all is ASCII."""
    return F.when(F.octet_length(s) == F.char_length(s), F.lower(s)).otherwise(F.translate(s, ascii_uppercase, ascii_lowercase))


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _key(line: Column) -> Column:
    return F.trim(line, F.lit(BLANKS))


def _digest(key: Column) -> Column:
    key = _lower_ascii(key)
    return F.struct(F.xxhash64(key).alias("a"), F.xxhash64(F.lit("line"), key).alias("b"))


def common_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5) -> tuple[DataFrame, DataFrame]:
    """(document, line) of the lines long enough, once each; and the common ones with their keeper."""
    held = (
        docs.select(F.col(id_col).alias("_id"), F.explode(_lines(F.col(text_col))).alias("_line"))
        .select("_id", _key(F.col("_line")).alias("_key"))
        .where(F.char_length("_key") >= min_chars)
        .select("_id", _digest(F.col("_key")).alias("_d"))
        .select("_id", F.col("_d.a").alias("_a"), F.col("_d.b").alias("_b"))
        .groupBy("_a", "_b", "_id").agg(F.count(F.lit(1)).alias("_times"))
    )
    common = (
        held.groupBy("_a", "_b")
        .agg(F.count(F.lit(1)).alias("_docs"), F.max("_id").alias("_keeper"))
        .where(F.col("_docs") >= min_docs)
    )
    return held, common


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """The documents with their text's common lines dropped, and _n_lines, _n_dropped."""
    docs, back = hide(docs, (id_col, text_col))
    held, common = common_lines(docs, id_col, text_col, min_chars, min_docs)
    gone = (
        held.join(common, ["_a", "_b"])
        .where(~F.col("_id").eqNullSafe(F.col("_keeper")))
        .select("_id", F.struct(F.col("_a").alias("a"), F.col("_b").alias("b")).alias("_d"))
        .groupBy("_id").agg(F.collect_set("_d").alias("_gone"))
        .select(F.col("_id").alias("_gone_id"), "_gone")
    )
    lines = _lines(F.col(text_col))
    # a long text has many lines and many to drop: these are looked up by a part of their hash
    parts = F.when(F.size("_gone") > 64, F.lit(256)).otherwise(F.lit(1))
    looked_up = F.transform(F.sequence(F.lit(0), parts - 1), lambda k: F.filter("_gone", lambda g: F.pmod(g["a"], parts) == k))

    def stays(at: Column) -> Column:
        key = _key(at["line"])
        own = _digest(key)
        return (F.char_length(key) < min_chars) | ~F.array_contains(F.get("_parts", F.pmod(own["a"], F.size("_parts")).cast("int")), own)

    placed = F.transform(lines, lambda line, i: F.struct(i.alias("pos"), line.alias("line")))
    kept = F.transform(F.filter(placed, stays), lambda at: at["line"])
    own = [F.col(f"`{c}`") for c in docs.columns]
    out = (
        docs.join(gone, docs[id_col].eqNullSafe(gone["_gone_id"]), "left")
        .withColumn("_parts", F.when(F.col("_gone").isNotNull(), looked_up))
        .withColumn("_kept", F.when(F.col("_gone").isNotNull(), kept))
        .withColumn("_n_lines", F.size(lines).cast("long"))
        .withColumn("_n_dropped", F.when(F.col("_gone").isNull(), F.lit(0)).otherwise(F.col("_n_lines") - F.size("_kept")).cast("long"))
        .withColumn(text_col, F.when(F.col("_n_dropped") == 0, F.col(text_col)).otherwise(F.array_join("_kept", "\n")))
        .select(*own, "_n_lines", "_n_dropped")
    )
    return give_back(out, back)
