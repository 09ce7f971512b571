"""The experiment workloads, trained ones and those with a fixed rater that SQL can follow."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.catalog.fragments import RANKED, RATER, ROWS, SCORE, Z, exact_sample, lin, stats
from gradsift.catalog.registry import query
from gradsift.catalog.selection import SHIFTED, fifth, ranked
from gradsift.functions import heuristics
from gradsift.functions.features import pool_text
from gradsift.functions.networks import linear
from gradsift.operators import pruning
from gradsift.operators.measures import auc
from gradsift.operators.ranking import rank_corpus
from gradsift.plans import experiments
from gradsift.sources import corpora
from gradsift.sources.staging import staged


def _trained(name: str):
    def q(spark: SparkSession, sf_dir: str) -> DataFrame:
        return experiments.run(name, spark, sf_dir)

    q.__name__ = f"exp_{name}_trained"
    q.__doc__ = experiments.EXPERIMENTS[name].__doc__
    query()(q)


for _name in experiments.EXPERIMENTS:
    _trained(_name)

_LABELLED = "SELECT m.method, count(*) AS k, round(avg(quality), 6) AS good, round(avg(toxic), 6) AS toxic FROM m JOIN labels USING (doc_id) GROUP BY m.method"
_SETS = {
    "random": "SELECT doc_id FROM r ORDER BY (('0x' || substr(md5('42:' || doc_id), 1, 8))::BIGINT), doc_id LIMIT (SELECT count(*) // 5 FROM r)",
    "top_k": "SELECT doc_id FROM r WHERE rank <= (SELECT count(*) // 5 FROM r)",
    "block_s40": "SELECT doc_id FROM r WHERE pct >= 0.4 AND pct < 0.6 - 1e-12",
    "centred": exact_sample(0.0, 0.5, 0.2, "count(*) // 5"),
    "shifted": exact_sample(0.2, 0.6, 0.2, "count(*) // 5"),
}


def _labelled(stack: DataFrame, spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = corpora.table(spark, sf_dir, "labels")
    return stack.join(labels, "doc_id").groupBy("method").agg(
        F.count(F.lit(1)).alias("k"), F.round(F.avg("quality"), 6).alias("good"), F.round(F.avg("toxic"), 6).alias("toxic")
    )


def _five(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    r = ranked(spark, sf_dir)
    sets = experiments.schemes(r, fifth(r), 0.2, blocks=False)
    return sets | {"block_s40": pruning.prune_block(r, 0.4, 0.2)}


@query(f"WITH {RANKED}, m AS (" + " UNION ALL ".join(f"SELECT '{k}' AS method, doc_id FROM ({s})" for k, s in _SETS.items()) + f") {_LABELLED}")
def exp_pruning_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _labelled(experiments.stacked(_five(spark, sf_dir), ["doc_id"]), spark, sf_dir)


@query(f"WITH {RANKED}, m AS (" + " UNION ALL ".join(f"SELECT 'shifted_{p}' AS method, doc_id FROM ({exact_sample(0.2, 0.6, 0.2, f'count(*) * {p} // 100')})" for p in (10, 20, 50)) + f") {_LABELLED}")
def exp_data_scale(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    n = r.count()
    sets = {f"shifted_{p}": pruning.prune_shifted_gaussian(r, n * p // 100, "doc_id", SHIFTED) for p in (10, 20, 50)}
    return _labelled(experiments.stacked(sets, ["doc_id"]), spark, sf_dir)


@query(f"WITH {RANKED}, k AS ({exact_sample(0.2, 0.6, 0.2, 'count(*) // 5')}) SELECT least(floor(pct * 5), 4)::INT AS region, count(*) AS n, count(k.doc_id) AS kept, round(avg(x3), 6) AS distinct_words, round(avg(x2), 6) AS upper, min(r.doc_id) AS first_id FROM r LEFT JOIN k ON k.doc_id = r.doc_id GROUP BY 1")
def exp_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per fifth of the ranking: what is kept, and what its texts look like."""
    from gradsift.functions.features import text_statistics

    r = ranked(spark, sf_dir)
    kept = pruning.prune_shifted_gaussian(r, fifth(r), "doc_id", SHIFTED).select("doc_id").withColumn("_kept", F.lit(1))
    s = text_statistics(F.col("text"))
    shape = corpora.table(spark, sf_dir, "documents").select("doc_id", s["distinct"].alias("distinct"), s["upper"].alias("upper"))
    region = F.least(F.floor(F.col("pct") * 5), F.lit(4)).cast("int").alias("region")
    return r.join(kept, "doc_id", "left").join(shape, "doc_id").groupBy(region).agg(
        F.count(F.lit(1)).alias("n"), F.count("_kept").alias("kept"), F.round(F.avg("distinct"), 6).alias("distinct_words"),
        F.round(F.avg("upper"), 6).alias("upper"), F.min("doc_id").alias("first_id"),
    )


@query("""WITH j AS (SELECT l.doc_id, d.lang, l.quality = 1 AS preferred, row_number() OVER (PARTITION BY d.lang, l.quality = 1 ORDER BY l.doc_id) AS nth FROM labels l JOIN documents d USING (doc_id)),
    c AS (SELECT lang, least(count(*) FILTER (preferred), count(*) FILTER (NOT preferred)) AS m FROM j GROUP BY lang)
    SELECT j.lang || '-' || nth AS prompt_id, j.lang, doc_id AS item_id, preferred FROM j JOIN c USING (lang) WHERE nth <= m""")
def preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.preference_pairs(spark, sf_dir)


@query("SELECT page_id AS doc_id, trim(regexp_replace(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<[^>]*>', ' ', 'g'), '[ \\n\\t]+', ' ', 'g')) AS text, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS source FROM pages")
def pages_to_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpora.page_corpus(spark, sf_dir)


@query()
def exp_web_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages stripped, rated and pruned by the five schemes: size and mean length of each."""
    pages = pool_text(corpora.page_corpus(spark, sf_dir))
    rows = staged(pages.select("doc_id", F.char_length("text").alias("chars"), linear(F.col("features"), (0.3, -1.0, 0.8, -0.6, -0.3, -0.1)).alias("score")))
    r = staged(rank_corpus(rows, "score", "doc_id"), "ranks")
    stack = experiments.stacked(experiments.schemes(r, r.count() // 5, 0.2), ["doc_id", "chars"])
    return stack.groupBy("method").agg(F.count(F.lit(1)).alias("k"), F.avg("chars").alias("mean_chars"))


W = (0.6, -0.2, 0.4)
_ROWRANK = f"{ROWS}, s AS (SELECT sample_id AS doc_id, {lin(W)} AS score FROM l), r AS (SELECT *, row_number() OVER (ORDER BY score DESC, doc_id) AS rank, (row_number() OVER (ORDER BY score DESC, doc_id) - 1) / count(*) OVER ()::DOUBLE AS pct FROM s)"


@query(f"WITH {_ROWRANK} SELECT doc_id AS sample_id FROM ({exact_sample(0.2, 0.6, 0.2, 'count(*) // 5')})")
def bench_lineitem_select(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items rated, ranked and sampled: the scale bench."""
    rows = staged(corpora.row_corpus(spark, sf_dir).select("sample_id", linear(F.col("features"), W).alias("score")))
    r = staged(rank_corpus(rows, "score", "sample_id"), "ranks")
    return pruning.prune_shifted_gaussian(r, r.count() // 5, "sample_id", SHIFTED).select("sample_id")


@query()
def exp_proxy_kind(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spread of a sample's loss over noise levels, against none for the single-step proxy."""
    from gradsift.operators import proxies

    rows = corpora.raster_corpus(spark, sf_dir)
    losses = rows.select("sample_id", F.array(*(proxies.denoise_loss(F.col("pixels"), "sample_id", t) for t in range(5))).alias("by_level"), proxies.scale_loss(F.col("pixels")).alias("one_step"))
    mean = F.aggregate("by_level", F.lit(0.0), lambda a, x: a + x) / 5
    second = F.aggregate("by_level", F.lit(0.0), lambda a, x: a + x * x) / 5
    return losses.agg(
        F.avg(F.sqrt(F.greatest(second - mean * mean, F.lit(0.0))) / mean).alias("spread_over_levels"), F.avg(mean).alias("denoise_loss"),
        F.avg("one_step").alias("one_step_loss"), F.lit(0.0).alias("one_step_spread"),
    )


@query()
def rater_auc_trained(spark: SparkSession, sf_dir: str) -> DataFrame:
    """AUC of the trained rater (gap rule, group part) against quality, over the training pool."""
    pool = experiments.rate_in_batches(pool_text(corpora.train_pool(spark, sf_dir)), experiments.train_rater(spark, sf_dir).rater)
    labels = corpora.table(spark, sf_dir, "labels").select("doc_id", "quality")
    return auc(pool.join(labels, "doc_id"), "score", "quality")


@query()
def rate_trained(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole corpus rated once by the trained rater, instance and group part."""
    rater = experiments.train_rater(spark, sf_dir).rater
    return experiments.rate_in_batches(corpora.text_corpus(spark, sf_dir), rater)




_HALF = "(SELECT count(*) // 2 FROM r)"
_BY = {
    "aesthetic": "1 / (1 + exp(-(" + " + ".join(f"{zi} * ({w}::DOUBLE)" for zi, w in zip(Z, heuristics.AESTHETIC, strict=True)) + ")))",
    "clarity": "length(regexp_replace(t, '[#*$%&|<>]', '', 'g'))::DOUBLE / length(t)",
    "edges": "(length(t) - length(regexp_replace(t, '[\\n.,;:!?]', '', 'g')))::DOUBLE / length(t)",
    "distinct": "x3",
}
_ALL = {
    "full": "SELECT doc_id FROM r", "random": f"SELECT doc_id FROM r ORDER BY (('0x' || substr(md5('42:' || doc_id), 1, 8))::BIGINT), doc_id LIMIT {_HALF}",
    **{k: f"SELECT doc_id FROM r ORDER BY round({e}, 9) DESC, doc_id LIMIT {_HALF}" for k, e in _BY.items()},
    "shifted_20": exact_sample(0.2, 0.6, 0.2, "count(*) // 5"), "shifted_50": exact_sample(0.2, 0.6, 0.2, "count(*) // 2"),
}


@query(f"WITH {RANKED}, m AS (" + " UNION ALL ".join(f"SELECT '{k}' AS method, doc_id FROM ({s})" for k, s in _ALL.items()) + f") {_LABELLED}")
def exp_method_comparison(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full, random, four single metrics at half and the method at a fifth and a half: size and labels of what is kept."""
    r, f = ranked(spark, sf_dir), F.col("features")
    n = r.count()
    scores = staged(corpora.text_corpus(spark, sf_dir).select(
        "doc_id", F.round(heuristics.aesthetic(f), 9).alias("aesthetic"), F.round(heuristics.text_clarity(F.col("text")), 9).alias("clarity"),
        F.round(heuristics.text_edges(F.col("text")), 9).alias("edges"), F.round(f[2] * F.lit(0.2) + F.lit(0.7), 9).alias("distinct"),
    ))
    sets = {"full": r, "random": pruning.prune_random(r, n // 2, "doc_id")}
    for name in _BY:
        sets[name] = pruning.prune_top_k(rank_corpus(scores.select("doc_id", name), name, "doc_id"), n // 2)
    for name, k in (("shifted_20", n // 5), ("shifted_50", n // 2)):
        sets[name] = pruning.prune_shifted_gaussian(r, k, "doc_id", SHIFTED)
    return _labelled(experiments.stacked(sets, ["doc_id"]), spark, sf_dir)


_PAIRS = """j AS (SELECT l.doc_id, d.lang, l.quality = 1 AS preferred, row_number() OVER (PARTITION BY d.lang, l.quality = 1 ORDER BY l.doc_id) AS nth FROM labels l JOIN documents d USING (doc_id)),
    pc AS (SELECT lang, least(count(*) FILTER (preferred), count(*) FILTER (NOT preferred)) AS most FROM j GROUP BY lang), it AS (SELECT j.doc_id, preferred FROM j JOIN pc USING (lang) WHERE nth <= most)"""


def _rank_sql(source: str) -> str:
    return f"rr AS (SELECT *, row_number() OVER (ORDER BY score DESC, doc_id) AS rank, (row_number() OVER (ORDER BY score DESC, doc_id) - 1) / count(*) OVER ()::DOUBLE AS pct FROM {source})"


def _two_shares(counted: str) -> str:
    parts = []
    for p in (20, 50):
        parts.append(f"SELECT 'random_{p}' AS method, doc_id FROM (SELECT doc_id FROM rr ORDER BY (('0x' || substr(md5('42:' || doc_id), 1, 8))::BIGINT), doc_id LIMIT (SELECT count(*) * {p} // 100 FROM rr))")
        parts.append(f"SELECT 'shifted_{p}' AS method, doc_id FROM ({exact_sample(0.2, 0.6, 0.2, f'count(*) * {p} // 100', source='rr')})")
    return f"m AS ({' UNION ALL '.join(parts)}) {counted}"


def _two(r: DataFrame) -> DataFrame:
    n, sets = r.count(), {}
    for p in (20, 50):
        sets |= experiments.random_and_shifted(r, n * p // 100, 42, f"_{p}")
    return experiments.stacked(sets, ["doc_id"])


@query(f"WITH {RANKED}, {_PAIRS}, sc AS (SELECT s.doc_id, score, preferred FROM s JOIN it USING (doc_id)), {_rank_sql('sc')}, " + _two_shares("SELECT method, count(*) AS k, round(avg(preferred::INT), 6) AS preferred FROM m JOIN rr USING (doc_id) GROUP BY method"))
def exp_mixed_domain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Preferred and non-preferred documents, mixed: how many of the kept ones are preferred."""
    items = corpora.preference_pairs(spark, sf_dir).select(F.col("item_id").alias("doc_id"), "preferred")
    rows = staged(corpora.text_corpus(spark, sf_dir).select("doc_id", linear(F.col("features"), RATER).alias("score")).join(items, "doc_id"))
    kept = _two(staged(rank_corpus(rows, "score", "doc_id"), "ranks"))
    return kept.join(items, "doc_id").groupBy("method").agg(F.count(F.lit(1)).alias("k"), F.round(F.avg(F.col("preferred").cast("int")), 6).alias("preferred"))


@query("WITH c0 AS (SELECT conv_id * 1000 + turn AS doc_id, text, role FROM conversations), " + stats("c0") + f", sc AS (SELECT doc_id, role, {SCORE} AS score FROM f), {_rank_sql('sc')}, " + _two_shares("SELECT method, count(*) AS k, round(avg((role = 'assistant')::INT), 6) AS assistant FROM m JOIN rr USING (doc_id) GROUP BY method"))
def exp_second_domain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversation turns rated by the documents' rater: what is kept, by role."""
    turns = pool_text(corpora.dialogue_corpus(spark, sf_dir))
    rows = staged(turns.select("doc_id", "source", linear(F.col("features"), RATER).alias("score")))
    kept = _two(staged(rank_corpus(rows, "score", "doc_id"), "ranks"))
    return kept.join(rows, "doc_id").groupBy("method").agg(F.count(F.lit(1)).alias("k"), F.round(F.avg((F.col("source") == "assistant").cast("int")), 6).alias("assistant"))


#: Group weights over the means and variances of the six statistics, and a bias.
GROUP = (0.2, -0.4, 0.3, -0.2, -0.1, 0.05, 0.1, -0.1, 0.2, -0.05, 0.02, 0.03, 0.1)
_D = ", ".join(f"avg({zi}) AS dm{i}" for i, zi in enumerate(Z)) + ", " + ", ".join(f"var_pop({zi}) AS dv{i}" for i, zi in enumerate(Z))
_GZ = " + ".join(f"dm{i} * ({GROUP[i]}::DOUBLE) + dv{i} * ({GROUP[6 + i]}::DOUBLE)" for i in range(6)) + f" + {GROUP[12]}::DOUBLE"
_ABL = f"""bt AS (SELECT *, ('0x' || substr(md5('42:' || doc_id), 1, 8))::BIGINT % (SELECT ceil(count(*) / 64.0)::BIGINT FROM r) AS batch_id FROM r), de AS (SELECT batch_id, {_D} FROM bt GROUP BY batch_id),
    sc AS (SELECT doc_id, score + ln(1 / (1 + exp(-({_GZ})))) AS score FROM bt JOIN de USING (batch_id)), {_rank_sql('sc')}"""
_ABL_SETS = {"top_k": _SETS["top_k"], "centred": _SETS["centred"], "shifted": _SETS["shifted"], "shifted_group": exact_sample(0.2, 0.6, 0.2, "count(*) // 5", source="rr")}


@query(f"WITH {RANKED}, {_ABL}, m AS (" + " UNION ALL ".join(f"SELECT '{k}' AS method, doc_id FROM ({s})" for k, s in _ABL_SETS.items()) + f") {_LABELLED}")
def exp_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Top-K, centred and shifted by instance score, and shifted by instance and batch score."""
    from gradsift.functions.networks import sigmoid
    from gradsift.operators.batching import assign_batches
    from gradsift.operators.rating import batch_descriptor, rate

    rows = staged(assign_batches(corpora.text_corpus(spark, sf_dir).select("doc_id", "features", linear(F.col("features"), RATER).alias("raw")), "doc_id"))
    z = linear(F.col("descriptor"), GROUP[:12], GROUP[12])
    batches = batch_descriptor(rows, "features", 6).select("batch_id", sigmoid(z).alias("batch_weight"))
    alone = staged(rank_corpus(rows.select("doc_id", F.col("raw").alias("score")), "score", "doc_id"), "ranks")
    both = staged(rank_corpus(rate(rows, "raw", "logit_group", batches).select("doc_id", "score"), "score", "doc_id"), "ranks")
    k = fifth(alone)
    sets = {
        "top_k": pruning.prune_top_k(alone, k), "centred": pruning.prune_gaussian(alone, k, "doc_id"),
        "shifted": pruning.prune_shifted_gaussian(alone, k, "doc_id", SHIFTED), "shifted_group": pruning.prune_shifted_gaussian(both, k, "doc_id", SHIFTED),
    }
    return _labelled(experiments.stacked(sets, ["doc_id"]), spark, sf_dir)
