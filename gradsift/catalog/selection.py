"""Rating, ranking and pruning of documents with a fixed rater."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.catalog.fragments import RANKED, RATER, Z, exact_sample, gaussian, stats, u
from gradsift.catalog.registry import query
from gradsift.functions.networks import linear, mlp
from gradsift.operators import batching, pruning
from gradsift.operators.batching import assign_batches
from gradsift.operators.pruning import ShiftedGaussian
from gradsift.operators.ranking import approx_percentile_of, rank_corpus, splitters
from gradsift.plans.rater import FIXED_MLP
from gradsift.sources.corpora import text_corpus
from gradsift.sources.staging import staged

SHIFTED = ShiftedGaussian()


def rated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, features, score of the fixed linear rater: one map-only scan."""
    return text_corpus(spark, sf_dir).select("doc_id", "lang", "source", "features", linear(F.col("features"), RATER).alias("score"))


def ranked(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, score, rank, pct. The texts are read once, for the ratings; ranks are written too."""
    ratings = staged(rated(spark, sf_dir).select("doc_id", "score"))
    return staged(rank_corpus(ratings, "score", "doc_id"), "ranks")


def fifth(df: DataFrame) -> int:
    return df.count() // 5


@query(f"WITH {RANKED} SELECT doc_id, round(score, 6) AS score FROM r")
def rate_linear(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rated(spark, sf_dir).select("doc_id", F.round("score", 6).alias("score"))


_W1, _B1, _W2, _B2 = FIXED_MLP
_MLP = f"{_B2}::DOUBLE" + "".join(
    f" + tanh({b}::DOUBLE" + "".join(f" + {zi} * ({w}::DOUBLE)" for zi, w in zip(Z, row, strict=True)) + f") * ({v}::DOUBLE)"
    for row, b, v in zip(_W1.tolist(), _B1.tolist(), _W2.tolist(), strict=True)
)


@query(f"WITH {stats()} SELECT doc_id, round({_MLP}, 6) AS score FROM f")
def rate_mlp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_corpus(spark, sf_dir).select("doc_id", F.round(mlp(F.col("features"), *FIXED_MLP), 6).alias("score"))


@query(f"WITH {RANKED} SELECT doc_id, rank, round(pct, 6) AS pct FROM r")
def global_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ranked(spark, sf_dir).select("doc_id", "rank", F.round("pct", 6).alias("pct"))


@query()
def approximate_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Percentiles from a snapshot's cuts, without an exchange."""
    scored = rated(spark, sf_dir).select("doc_id", "score")
    return approx_percentile_of(scored, "score", splitters(scored, "score", 200))


@query(f"WITH {RANKED}, g AS (SELECT *, {gaussian(0.2, 0.6, 0.2)} AS g FROM r) SELECT doc_id, round(g, 6) AS g, round(g / sum(g) OVER () * 1000, 6) AS p1000 FROM g")
def gaussian_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = pruning.gaussian_density(ranked(spark, sf_dir), SHIFTED)
    return out.select("doc_id", F.round("g", 6).alias("g"), F.round(F.col("p") * 1000, 6).alias("p1000"))


@query(f"WITH {RANKED} SELECT doc_id FROM r WHERE rank <= (SELECT count(*) // 5 FROM r)")
def prune_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    return pruning.prune_top_k(r, fifth(r)).select("doc_id")


@query(f"WITH {RANKED} SELECT doc_id FROM r WHERE pct >= 0.4 AND pct < 0.6 - 1e-12")
def prune_block(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pruning.prune_block(ranked(spark, sf_dir), 0.4, 0.2).select("doc_id")


@query(f"WITH {RANKED} SELECT k.start, count(*) AS n, sum(doc_id)::BIGINT AS ids FROM r, (SELECT unnest([0, 10, 20, 30, 40, 50, 60, 70, 80]) AS start) k WHERE pct >= k.start / 100.0::DOUBLE AND pct < (k.start / 100.0::DOUBLE + 0.2::DOUBLE) - 1e-12 GROUP BY k.start")
def prune_block_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    grid = spark.createDataFrame([(s, s / 100) for s in range(0, 81, 10)], "start int, lo double")
    r = ranked(spark, sf_dir).select("doc_id", "pct").crossJoin(F.broadcast(grid))
    return r.where((F.col("pct") >= F.col("lo")) & (F.col("pct") < F.col("lo") + 0.2 - 1e-12)).groupBy("start").agg(F.count(F.lit(1)).alias("n"), F.sum("doc_id").alias("ids"))


@query(f"WITH {RANKED} {exact_sample(0.0, 0.5, 0.2, 'count(*) // 5')}")
def prune_centered_gaussian(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    return pruning.prune_gaussian(r, fifth(r), "doc_id").select("doc_id")


@query(f"WITH {RANKED} {exact_sample(0.2, 0.6, 0.2, 'count(*) // 5')}")
def prune_shifted_gaussian(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    return pruning.prune_shifted_gaussian(r, fifth(r), "doc_id", SHIFTED).select("doc_id")


_BINS = f"""bn AS (SELECT *, floor(pct * 100)::INT AS q, {gaussian(0.2, 0.6, 0.2)} AS g, {u('doc_id', 42)} AS h FROM r WHERE pct >= 0.2), kk AS (SELECT count(*) // 5 AS k FROM r),
    qs AS (SELECT q, k * sum(g) / (SELECT sum(g) FROM bn) AS share, count(*) AS room FROM bn, kk GROUP BY q, k)"""


# at a fifth no bin's quota exceeds its rows, so shares are rounded by largest remainders
@query(f"""WITH {RANKED}, {_BINS}, rm AS (SELECT *, row_number() OVER (ORDER BY share - floor(share) DESC, q) AS nth FROM qs),
    tk AS (SELECT q, floor(share) + (nth <= (SELECT k FROM kk) - (SELECT sum(floor(share)) FROM qs))::INT AS take FROM rm),
    od AS (SELECT doc_id, q, row_number() OVER (PARTITION BY q ORDER BY h, doc_id) AS nth FROM bn) SELECT doc_id FROM od JOIN tk USING (q) WHERE nth <= take""")
def prune_shifted_quota(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    return pruning.prune_shifted_gaussian(r, fifth(r), "doc_id", SHIFTED, "quota").select("doc_id")


# nor is any probability cut at 1
@query(f"WITH {RANKED}, {_BINS} SELECT doc_id FROM bn, kk WHERE h < least(1, g * k / (SELECT sum(g) FROM bn))")
def prune_shifted_poisson(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    return pruning.prune_shifted_gaussian(r, fifth(r), "doc_id", SHIFTED, "poisson").select("doc_id")


@query(f"SELECT doc_id FROM documents ORDER BY {u('doc_id', 42)}, doc_id LIMIT (SELECT count(*) // 5 FROM documents)")
def prune_random(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id")
    return pruning.prune_random(docs, fifth(docs), "doc_id").select("doc_id")


@query("SELECT doc_id, lang, source FROM documents WHERE doc_id IN (SELECT min(doc_id) FROM documents GROUP BY coalesce(text, ''))")
def dedup_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of equal texts, the one with the smallest id."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang", "source")
    return batching.dedup_exact(docs).select("doc_id", "lang", "source")


@query("SELECT doc_id FROM documents")
def prune_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pruning.prune_none(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id"))


@query(f"WITH {RANKED}, k AS ({exact_sample(0.2, 0.6, 0.2, 'count(*) // 5')}) SELECT least(floor(pct * 20), 19)::INT AS bin, count(*) AS n, count(k.doc_id) AS kept, round(count(k.doc_id)::DOUBLE / count(*), 6) AS share FROM r LEFT JOIN k ON k.doc_id = r.doc_id GROUP BY 1")
def selection_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    kept = pruning.prune_shifted_gaussian(r, fifth(r), "doc_id", SHIFTED)
    return pruning.selection_histogram(r, kept, "doc_id").withColumn("share", F.round("share", 6))


GRID = [(0, 0.0, 0.5, 0.2), (1, 0.2, 0.6, 0.2), (2, 0.1, 0.6, 0.15), (3, 0.2, 0.7, 0.2), (4, 0.3, 0.65, 0.1)]


@query(f"WITH {RANKED} " + " UNION ALL ".join(f"SELECT {c} AS config, count(*) AS n, sum(doc_id)::BIGINT AS ids FROM ({exact_sample(d, m, s, 'count(*) // 5')})" for c, d, m, s in GRID))
def pruning_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    grid = spark.createDataFrame(GRID, "config int, discard double, mean double, spread double")
    return pruning.sweep_pruning(r, grid, fifth(r), "doc_id").groupBy("config").agg(F.count(F.lit(1)).alias("n"), F.sum("doc_id").alias("ids"))


@query(f"SELECT doc_id, floor((row_number() OVER (ORDER BY {u('doc_id', 42)}, doc_id) - 1) / 64)::BIGINT AS batch_id FROM documents")
def minibatch_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id")
    return assign_batches(docs, "doc_id", how="exact").select("doc_id", F.col("batch_id").cast("long").alias("batch_id"))


@query("SELECT doc_id, ('0x' || substr(md5('42:' || doc_id), 1, 8))::BIGINT % (SELECT ceil(count(*) / 64.0)::BIGINT FROM documents) AS batch_id FROM documents")
def minibatch_hashed(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id")
    return assign_batches(docs, "doc_id")


@query(f"WITH {stats()} SELECT doc_id, " + ", ".join(f"round({zi}, 6) AS z{i + 1}" for i, zi in enumerate(Z)) + " FROM f")
def pooled_text_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_corpus(spark, sf_dir).select("doc_id", *(F.round(F.col("features")[i], 6).alias(f"z{i + 1}") for i in range(6)))


