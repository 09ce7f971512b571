"""Corpora bound to tables. Each reads only the columns it names."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.functions.features import pool_text, raster
from gradsift.functions.hashing import hash_uniform
from gradsift.operators.batching import without_copies


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, text, lang, source, n_chars, features."""
    return pool_text(table(spark, sf_dir, "documents"))


def row_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sample_id, features (quantity, discount, tax, scaled), target (price, scaled). The id is unique."""
    l = table(spark, sf_dir, "lineitem")
    key = F.concat_ws("-", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.date_format("l_shipdate", "yyyyMMdd"))
    x = [F.col("l_quantity").cast("double") / 50, F.col("l_discount").cast("double") * 10, F.col("l_tax").cast("double") * 10]
    return l.select(key.alias("sample_id"), F.array(*x).alias("features"), (F.col("l_extendedprice").cast("double") / 100000).alias("target"))


def raster_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sample_id, pixels (8 x 8), label."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("sample_id"), raster(F.col("embedding")).alias("pixels"), "label")


def wanted(spark: SparkSession, sf_dir: str, seed: int = 7, share: float = 0.5) -> DataFrame:
    """Documents of the wanted kind: a hash share of those labelled good and harmless."""
    labels = table(spark, sf_dir, "labels").where("quality = 1 AND toxic = 0").select("doc_id")
    return table(spark, sf_dir, "documents").join(labels, "doc_id", "left_semi").where(hash_uniform("doc_id", seed) < share)


def train_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that are neither validation documents nor copies of one."""
    val = wanted(spark, sf_dir)
    docs = table(spark, sf_dir, "documents")
    return without_copies(docs.join(val.select("doc_id"), "doc_id", "left_anti"), val)


def dialogue_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    return c.select((F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), "text", F.col("role").alias("source"))


def page_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages with scripts, styles and tags taken out, and their host."""
    p = table(spark, sf_dir, "pages")
    bare = F.regexp_replace(F.regexp_replace("html", "(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), "<[^>]*>", " ")
    return p.select(F.col("page_id").alias("doc_id"), F.trim(F.regexp_replace(bare, "[ \\n\\t]+", " ")).alias("text"), F.parse_url("url", F.lit("HOST")).alias("source"))


def preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per language the k-th good document with the k-th bad one: prompt_id, lang, item_id, preferred.

    Numbering is by language over labelled documents; languages are few, so numbers come
    from ranks within hash bins of the language and the bins' counts.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang")
    rated = table(spark, sf_dir, "labels").join(docs, "doc_id").select("doc_id", "lang", (F.col("quality") == 1).alias("preferred"))
    numbered = number_within(rated, ["lang", "preferred"], "doc_id")
    sizes = numbered.groupBy("lang").agg(F.count_if("preferred").alias("good"), F.count_if(~F.col("preferred")).alias("bad"))
    both = numbered.join(F.broadcast(sizes), "lang").where(F.col("nth") <= F.least("good", "bad"))
    return both.select(F.concat_ws("-", "lang", F.col("nth").cast("string")).alias("prompt_id"), "lang", F.col("doc_id").alias("item_id"), "preferred")


def number_within(df: DataFrame, keys: list[str], order: str, width: int = 4096) -> DataFrame:
    """Adds nth, from 1, by order within each key. No task sorts more than a range of the order column.

    Ranges of width values are counted, the counts summed up over the ranges of each key, and
    rows numbered within their range.
    """
    from pyspark.sql import Window

    ranged = df.withColumn("_r", F.floor(F.col(order) / width))
    counts = ranged.groupBy(*keys, "_r").agg(F.count(F.lit(1)).alias("_n"))
    upto = counts.withColumn("_before", F.coalesce(F.sum("_n").over(Window.partitionBy(*keys).orderBy("_r").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("_n")
    within = Window.partitionBy(*keys, "_r").orderBy(order)
    return ranged.withColumn("_i", F.row_number().over(within)).join(upto, [*keys, "_r"]).withColumn("nth", F.col("_before") + F.col("_i")).drop("_r", "_i", "_before")
