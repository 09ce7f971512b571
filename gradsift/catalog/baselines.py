"""Single-metric baselines: the raster forms, their text stand-ins, and combinations."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.catalog.fragments import Z, stats
from gradsift.catalog.registry import query
from gradsift.catalog.selection import fifth
from gradsift.functions import heuristics
from gradsift.operators import pruning
from gradsift.operators.ranking import rank_corpus
from gradsift.operators.rating import combine_scores
from gradsift.plans.experiments import heuristic_ranks, three_ways
from gradsift.sources.corpora import raster_corpus, table, text_corpus


def _p(r: int, c: int) -> str:
    return f"embedding[{r * 8 + c + 1}]::DOUBLE"


_LAP = [f"({_p(r - 1, c)} + {_p(r + 1, c)} + {_p(r, c - 1)} + {_p(r, c + 1)} - 4.0::DOUBLE * {_p(r, c)})" for r in range(1, 7) for c in range(1, 7)]


@query(f"SELECT vec_id AS sample_id, round(list_var_pop([{', '.join(_LAP)}]) * 100, 6) AS clarity100 FROM embeddings")
def score_clarity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return raster_corpus(spark, sf_dir).select("sample_id", F.round(heuristics.clarity(F.col("pixels")) * 100, 6).alias("clarity100"))


def _basis(k: str, i: str) -> str:
    return f"sqrt(CASE WHEN {k} = 0 THEN 0.125 ELSE 0.25 END) * cos({math.pi!r}::DOUBLE * (2 * {i} + 1) * {k} / 16)"


@query(f"""WITH x AS (SELECT vec_id, i // 8 AS r, i % 8 AS c, embedding[i + 1]::DOUBLE AS v FROM embeddings, (SELECT unnest(range(0, 64)) AS i)),
    a AS (SELECT vec_id, r, k AS kc, sum(v * {_basis('k', 'c')}) AS v FROM x, (SELECT unnest(range(0, 8)) AS k) GROUP BY vec_id, r, k),
    b AS (SELECT vec_id, kc, k AS kr, sum(v * {_basis('k', 'r')}) AS v FROM a, (SELECT unnest(range(0, 8)) AS k) GROUP BY vec_id, kc, k)
    SELECT vec_id AS sample_id, round(sum(v * v) FILTER (kr + kc >= 8) / sum(v * v) FILTER (kr + kc > 0), 6) AS high_share FROM b GROUP BY vec_id""")
def score_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    return raster_corpus(spark, sf_dir).select("sample_id", F.round(heuristics.frequency(F.col("pixels")), 6).alias("high_share"))


_EDGE = [f"(pow({_p(r, c + 1)} - {_p(r, c)}, 2) + pow({_p(r + 1, c)} - {_p(r, c)}, 2) > 0.01)::INT" for r in range(7) for c in range(7)]


@query(f"SELECT vec_id AS sample_id, round(({' + '.join(_EDGE)}) / 49.0::DOUBLE, 6) AS edges FROM embeddings")
def score_edge_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    return raster_corpus(spark, sf_dir).select("sample_id", F.round(heuristics.edge_density(F.col("pixels")), 6).alias("edges"))


_AES = " + ".join(f"{zi} * ({w}::DOUBLE)" for zi, w in zip(Z, heuristics.AESTHETIC, strict=True))


@query(f"WITH {stats()} SELECT doc_id, round(1 / (1 + exp(-({_AES}))), 6) AS aesthetic FROM f")
def score_aesthetic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_corpus(spark, sf_dir).select("doc_id", F.round(heuristics.aesthetic(F.col("features")), 6).alias("aesthetic"))


@query()
def score_aesthetic_fitted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The linear estimator fitted to the quality labels."""
    from gradsift.plans.downstream import fit_estimator

    corpus = text_corpus(spark, sf_dir)
    weights, bias = fit_estimator(corpus.join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id"), "features", "quality")
    return corpus.select("doc_id", heuristics.aesthetic(F.col("features"), tuple(weights), bias).alias("aesthetic"))


@query("SELECT doc_id, round(length(regexp_replace(text, '[#*$%&|<>]', '', 'g'))::DOUBLE / length(text), 6) AS clarity, round((length(text) - length(regexp_replace(text, '[\\n.,;:!?]', '', 'g')))::DOUBLE / length(text), 6) AS edges FROM documents")
def score_text_standins(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return docs.select("doc_id", F.round(heuristics.text_clarity(F.col("text")), 6).alias("clarity"), F.round(heuristics.text_edges(F.col("text")), 6).alias("edges"))


@query("""WITH w AS (SELECT doc_id, unnest(list_filter(string_split_regex(lower(text), '[ \\n]'), lambda x: x <> '')) AS w FROM documents),
    d AS (SELECT w, count(DISTINCT doc_id) AS df FROM w GROUP BY w)
    SELECT doc_id, round(count(*) FILTER (df <= 3)::DOUBLE / count(*), 6) AS rare_share FROM w JOIN d USING (w) GROUP BY doc_id""")
def score_rare_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The text stand-in of the frequency metric: share of words that at most three documents have."""
    return heuristics.rare_word_share(table(spark, sf_dir, "documents")).select("doc_id", F.round("rare_share", 6).alias("rare_share"))


@query(f"WITH {stats()} SELECT doc_id FROM f WHERE round(1 / (1 + exp(-({_AES}))), 9) >= 0.5")
def threshold_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_corpus(spark, sf_dir).where(F.round(heuristics.aesthetic(F.col("features")), 9) >= 0.5).select("doc_id")


from gradsift.catalog.steps import COUNTS, LOGITS, doc_bigrams, logits  # noqa: E402
from gradsift.operators.proxies import bigram_loss  # noqa: E402


@query(f"WITH {COUNTS}, {LOGITS}, ll AS (SELECT doc_id, round(sum(n * (lse - value)) / sum(n), 9) AS loss FROM c JOIN lg USING (a, b) JOIN ls USING (a) GROUP BY doc_id) SELECT doc_id FROM ll ORDER BY loss, doc_id LIMIT (SELECT count(*) // 5 FROM ll)")
def one_stage_low_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rate by loss, lowest first, and take the top part."""
    losses = bigram_loss(doc_bigrams(spark, sf_dir), logits(spark), "doc_id").select("doc_id", F.round("loss", 9).alias("loss"))
    return pruning.prune_top_k(rank_corpus(losses, "loss", "doc_id", descending=False), fifth(losses)).select("doc_id")


_COMB = ("length(regexp_replace(t, '[#*$%&|<>]', '', 'g'))::DOUBLE / length(t)", "(length(t) - length(regexp_replace(t, '[\\n.,;:!?]', '', 'g')))::DOUBLE / length(t)", "x3")


@query(f"WITH {stats()}, k AS (SELECT doc_id, " + ", ".join(f"(row_number() OVER (ORDER BY {e} DESC, doc_id) - 1) / count(*) OVER ()::DOUBLE AS p{i}" for i, e in enumerate(_COMB)) + " FROM f) SELECT doc_id, round((3 - p0 - p1 - p2) / 3, 6) AS combined FROM k")
def combined_percentile_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    corpus = text_corpus(spark, sf_dir)
    scored = corpus.select(
        "doc_id", heuristics.text_clarity(F.col("text")).alias("clarity"), heuristics.text_edges(F.col("text")).alias("edges"),
        (F.col("features")[2] * F.lit(0.2) + F.lit(0.7)).alias("distinct"),
    ).withColumn("distinct", F.round("distinct", 12))
    return combine_scores(scored, ["clarity", "edges", "distinct"], "doc_id").select("doc_id", F.round("combined", 6).alias("combined"))


@query()
def best_heuristic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per heuristic, three ways to prune, held against the labels; the best is marked."""
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality")
    corpus = text_corpus(spark, sf_dir)
    out = None
    for name, r in heuristic_ranks(corpus).items():
        for way, kept in three_ways(r).items():
            row = kept.join(labels, "doc_id").agg(F.avg("quality").alias("value")).select(F.lit(name).alias("metric"), F.lit(way).alias("pruning"), "value")
            out = row if out is None else out.unionByName(row)
    best = out.groupBy("metric").agg(F.max("value").alias("_top"))
    return out.join(F.broadcast(best), "metric").withColumn("best", F.col("value") == F.col("_top")).drop("_top")


