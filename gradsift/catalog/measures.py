"""Cost and accuracy measures over fixed selections, curves and traces."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.catalog.fragments import RANKED, SCORE, Z, exact_sample, stats, u
from gradsift.catalog.registry import query
from gradsift.catalog.selection import SHIFTED, fifth, ranked, rated
from gradsift.catalog.steps import COUNTS, LOGITS, doc_bigrams, logits
from gradsift.catalog.workloads import _labelled
from gradsift.functions.hashing import hash_uniform
from gradsift.operators import measures, pruning
from gradsift.operators.proxies import bigram_loss
from gradsift.sources import corpora

SHIFT = f"k AS ({exact_sample(0.2, 0.6, 0.2, 'count(*) // 5')})"
TOP = "top AS (SELECT doc_id FROM r WHERE rank <= (SELECT count(*) // 5 FROM r))"


def shifted(r: DataFrame) -> DataFrame:
    return pruning.prune_shifted_gaussian(r, fifth(r), "doc_id", SHIFTED)


_F = ", ".join(f"avg(z{i}) AS m{i}, stddev_pop(z{i}) AS s{i}" for i in range(6))
_Z = ", ".join(f"{zi} AS z{i}" for i, zi in enumerate(Z))


@query(f"""WITH {RANKED}, {SHIFT}, q AS (SELECT doc_id, {_Z} FROM r), ka AS (SELECT {_F} FROM q SEMI JOIN k ON k.doc_id = q.doc_id), kb AS (SELECT {_F} FROM q)
    SELECT round({' + '.join(f'pow(ka.m{i} - kb.m{i}, 2) + pow(ka.s{i} - kb.s{i}, 2)' for i in range(6))}, 6) AS frechet FROM ka, kb""")
def frechet_diag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Text statistics of the shifted selection against those of the corpus."""
    corpus = rated(spark, sf_dir).select("doc_id", "features")
    kept = corpus.join(shifted(ranked(spark, sf_dir)).select("doc_id"), "doc_id", "left_semi")
    return measures.frechet_diagonal(kept, corpus, "features", 6).select(F.round("frechet", 6).alias("frechet"))


@query()
def frechet_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full covariances of rasters: a hash half against the other, and against itself."""
    rows = corpora.raster_corpus(spark, sf_dir).select("sample_id", "pixels")
    half = hash_uniform("sample_id", 3) < 0.5
    values = [("halves", measures.frechet_distance(rows.where(half), rows.where(~half), "pixels", 64)), ("same", measures.frechet_distance(rows, rows, "pixels", 64))]
    return spark.createDataFrame([(n, round(max(0.0, v), 6)) for n, v in values], "pair string, frechet double")


@query("""WITH p AS (SELECT e.vec_id, e.embedding::DOUBLE[] AS v, list_transform(range(1, 65), lambda i: CASE WHEN i <= 26 THEN (length(d.text) - length(replace(lower(d.text), chr((96 + i)::INT), '')))::DOUBLE ELSE 0::DOUBLE END) AS w
        FROM embeddings e JOIN documents d ON e.vec_id = d.doc_id)
    SELECT round(avg(list_dot_product(v, w) / sqrt(list_dot_product(v, v)) / sqrt(list_dot_product(w, w))), 6) AS alignment, count(*) AS pairs FROM p""")
def alignment_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean cosine of a raster's vector and its caption's letter counts."""
    # Spark lower-cases this one capital to two characters, which would shift every count
    low = F.lower(F.replace("text", F.lit("\u0130"), F.lit("i")))
    letters = [(F.char_length("text") - F.char_length(F.replace(low, F.lit(chr(96 + i)), F.lit("")))).cast("double") for i in range(1, 27)]
    texts = corpora.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"), F.array(*letters, *[F.lit(0.0)] * 38).alias("w"))
    pairs = corpora.raster_corpus(spark, sf_dir).select("sample_id", "pixels").join(texts, "sample_id")
    return measures.alignment_score(pairs, "pixels", "w").select(F.round("alignment", 6).alias("alignment"), "pairs")


def probes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One, two or three of an item's longer words, by the item's number."""
    items = corpora.table(spark, sf_dir, "benchmark").select("item_id", F.array_distinct(F.filter(F.split(F.lower("text"), "[^a-z0-9]+"), lambda w: F.char_length(w) >= 4)).alias("ws"))
    kind = (F.col("item_id") % 3 + 1).cast("int")
    return items.select(F.col("item_id").alias("probe_id"), kind.alias("kind"), F.slice("ws", F.lit(1), kind).alias("terms")).where(F.size("terms") == F.col("kind"))


@query(f"""WITH {RANKED}, {SHIFT}, d AS (SELECT doc_id, list_distinct(string_split_regex(lower(text), '[^a-z0-9]+')) AS ws FROM documents SEMI JOIN k USING (doc_id)),
    i AS (SELECT item_id, list_filter(string_split_regex(lower(text), '[^a-z0-9]+'), lambda w: length(w) >= 4) AS x FROM benchmark),
    j AS (SELECT item_id, (item_id % 3 + 1)::INT AS kind, list_filter(x, lambda w, n: list_position(x, w) = n) AS y FROM i),
    p AS (SELECT item_id, kind, y[1:kind] AS terms FROM j WHERE len(y) >= kind),
    o AS (SELECT kind, avg(CASE WHEN EXISTS (SELECT 1 FROM d WHERE list_has_all(d.ws, p.terms)) THEN 1.0 ELSE 0.0 END) AS rate FROM p GROUP BY kind)
    SELECT round(avg(rate), 6) AS compositional, count(*) AS kinds FROM o""")
def compositional_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = corpora.table(spark, sf_dir, "documents").select("doc_id", "text").join(shifted(ranked(spark, sf_dir)).select("doc_id"), "doc_id", "left_semi")
    return measures.compositional_score(kept, probes(spark, sf_dir)).select(F.round("compositional", 6).alias("compositional"), "kinds")


@query(f"""WITH {COUNTS}, {LOGITS}, v AS (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0 AND {u('doc_id', 7)} < 0.5),
    ll AS (SELECT doc_id, sum(n * (lse - value)) / sum(n) AS loss FROM c JOIN lg USING (a, b) JOIN ls USING (a) SEMI JOIN v USING (doc_id) GROUP BY doc_id) SELECT round(avg(loss), 6) AS val_loss, count(*) AS docs FROM ll""")
def downstream_val_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean loss of fixed downstream logits on the validation documents."""
    val = corpora.wanted(spark, sf_dir).select("doc_id")
    losses = bigram_loss(doc_bigrams(spark, sf_dir).join(val, "doc_id", "left_semi"), logits(spark), "doc_id")
    return losses.agg(F.round(F.avg("loss"), 6).alias("val_loss"), F.count(F.lit(1)).alias("docs"))


@query(f"WITH {RANKED}, {SHIFT} SELECT (SELECT count(*) FROM k) AS images, count(*) AS corpus, round((SELECT count(*) FROM k)::DOUBLE / count(*), 6) AS retention FROM r")
def retention(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    return measures.retention(shifted(r), r).withColumn("retention", F.round("retention", 6))


@query("SELECT count(*) // 5 AS images, count(*) // 5 * 3 AS visits, round((count(*) // 5 * 3) * 0.0078::DOUBLE / 3600, 9) AS hours FROM documents")
def training_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = corpora.table(spark, sf_dir, "documents").select("doc_id")
    kept = pruning.prune_random(docs, fifth(docs), "doc_id")
    return measures.training_cost(kept, 3, 0.0078).withColumn("hours", F.round("hours", 9))


#: Loss curves made from monthly order totals: elapsed is the month, the value falls and wavers.
_CURVES = """curves AS (SELECT 'm' || (extract(year FROM o_orderdate) % 3)::INT AS method, extract(month FROM o_orderdate)::INT AS epoch, extract(month FROM o_orderdate)::DOUBLE AS elapsed,
        round(20 - extract(month FROM o_orderdate) + avg(o_totalprice::DOUBLE) / 50000, 6) AS value FROM orders GROUP BY 1, 2, 3, extract(month FROM o_orderdate))"""


def curves(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = corpora.table(spark, sf_dir, "orders").select("o_orderdate", F.col("o_totalprice").cast("double").alias("p"))
    month = F.month("o_orderdate")
    method = F.concat(F.lit("m"), (F.year("o_orderdate") % 3).cast("int").cast("string"))
    return o.groupBy(method.alias("method"), month.alias("epoch")).agg(F.round(20 - F.first(month) + F.avg("p") / 50000, 6).alias("value")).withColumn("elapsed", F.col("epoch").cast("double"))


@query(f"""WITH {_CURVES}, b AS (SELECT method, elapsed, min(value) OVER (PARTITION BY method ORDER BY elapsed) AS best FROM curves), g AS (SELECT min(value) AS target FROM curves WHERE method = 'm1'),
    h AS (SELECT method, target, min(elapsed) AS elapsed FROM b, g WHERE best <= target GROUP BY method, target)
    SELECT a.method, a.target, a.elapsed, z.elapsed AS base_elapsed, round(z.elapsed / a.elapsed, 6) AS speedup FROM h a, h z WHERE z.method = 'm1' AND a.method <> 'm1'""")
def time_to_target(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.time_to_target(curves(spark, sf_dir), "m1").withColumn("speedup", F.round("speedup", 6))


@query(f"""WITH {_CURVES}, d AS (SELECT *, value - lag(value) OVER w AS d, min(value) OVER w AS best FROM curves WINDOW w AS (PARTITION BY method ORDER BY epoch)),
    t AS (SELECT *, CASE WHEN sign(d) * sign(lag(d) OVER (PARTITION BY method ORDER BY epoch)) < 0 THEN 1 ELSE 0 END AS turn FROM d) SELECT method, sum(turn)::BIGINT AS turns, round(max(value - best), 6) AS drawdown FROM t GROUP BY method""")
def curve_stability(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.curve_stability(curves(spark, sf_dir)).withColumn("drawdown", F.round("drawdown", 6))


#: Per-sample losses and gradient norms of a linear proxy at three recorded steps, by document.
STEPS = ((0, 0.0, 0.0), (1, 0.3, -0.2), (2, 0.5, -0.4))
_X = "(x3 - 0.7::DOUBLE)"
_Y = "x2"


def _trace_sql(extra: str = "") -> str:
    grid = ", ".join(f"({s}, {a}::DOUBLE, {b}::DOUBLE)" for s, a, b in STEPS)
    return f"{stats()}, st AS (SELECT * FROM (VALUES {grid}) AS g(step, ta, tb)), tr AS (SELECT doc_id, step, 0.5 * pow(ta + tb * {_X} - {_Y}, 2) AS loss, abs(ta + tb * {_X} - {_Y}) * sqrt(1 + {_X} * {_X}) AS grad_norm FROM f, st{extra})"


def trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, step, loss, grad_norm) of y = a + b x, with y the share of capitals and x of distinct words."""
    from gradsift.functions.features import text_statistics

    s = text_statistics(F.col("text"))
    rows = corpora.table(spark, sf_dir, "documents").select("doc_id", (s["distinct"] - F.lit(0.7)).alias("x"), s["upper"].alias("y"))
    grid = spark.createDataFrame(STEPS, "step int, ta double, tb double")
    r = F.col("ta") + F.col("tb") * F.col("x") - F.col("y")
    return rows.crossJoin(F.broadcast(grid)).select("doc_id", "step", (F.lit(0.5) * r * r).alias("loss"), (F.abs(r) * F.sqrt(F.lit(1.0) + F.col("x") * F.col("x"))).alias("grad_norm"))


@query(f"WITH {_trace_sql()} SELECT doc_id, step, round(loss, 6) AS loss FROM tr")
def loss_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trace(spark, sf_dir).select("doc_id", "step", F.round("loss", 6).alias("loss"))


@query(f"WITH {_trace_sql()} SELECT doc_id, step, round(grad_norm, 6) AS grad_norm FROM tr")
def gradnorm_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trace(spark, sf_dir).select("doc_id", "step", F.round("grad_norm", 6).alias("grad_norm"))


@query(f"""WITH {_trace_sql()}, s AS (SELECT doc_id, {SCORE} AS score FROM f), r AS (SELECT doc_id, (row_number() OVER (ORDER BY score DESC, doc_id) - 1) / count(*) OVER ()::DOUBLE AS pct FROM s),
    e AS (SELECT least(floor(pct * 10), 9)::INT AS bin, step, avg(loss) AS l, avg(grad_norm) AS g FROM tr JOIN r USING (doc_id) GROUP BY 1, 2)
    SELECT bin, round(avg(l), 6) AS mean_loss, round(avg(g), 6) AS mean_norm, round(regr_slope(l, step), 6) AS loss_slope, round(regr_slope(g, step), 6) AS norm_slope, round(arg_max(g, step) - arg_min(g, step), 6) AS norm_change FROM e GROUP BY bin""")
def dynamics_by_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = trace(spark, sf_dir).withColumnRenamed("step", "epoch")
    out = measures.dynamics_by_range(t, ranked(spark, sf_dir), "doc_id")
    return out.select("bin", *(F.round(c, 6).alias(c) for c in ("mean_loss", "mean_norm", "loss_slope", "norm_slope", "norm_change")))


@query(f"WITH {RANKED}, bb AS (SELECT doc_id, least(floor(pct * 10), 9)::INT AS bin, {u('doc_id', 42)} AS h FROM r), n AS (SELECT *, row_number() OVER (PARTITION BY bin ORDER BY h, doc_id) AS nth FROM bb) SELECT doc_id, bin FROM n WHERE nth <= 20")
def sample_across_ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.sample_across_ranges(ranked(spark, sf_dir), 20, "doc_id").select("doc_id", "bin")


_M = "m AS (SELECT 'random' AS method, doc_id FROM (SELECT doc_id FROM r ORDER BY (('0x' || substr(md5('42:' || doc_id), 1, 8))::BIGINT), doc_id LIMIT (SELECT count(*) // 5 FROM r)) UNION ALL SELECT 'top_k', doc_id FROM top UNION ALL SELECT 'shifted', doc_id FROM k)"


def three(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gradsift.plans.experiments import stacked

    r = ranked(spark, sf_dir)
    n = fifth(r)
    return stacked({"random": pruning.prune_random(r, n, "doc_id"), "top_k": pruning.prune_top_k(r, n), "shifted": shifted(r)}, ["doc_id"])


@query(f"WITH {RANKED}, {SHIFT}, {TOP}, {_M}, g AS (SELECT m.method, avg(quality) AS value FROM m JOIN labels USING (doc_id) GROUP BY m.method) SELECT method, round(value, 6) AS value, round(value - (SELECT value FROM g WHERE method = 'random'), 6) + 0 AS delta FROM g")
def delta_vs_random(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = corpora.table(spark, sf_dir, "labels")
    results = three(spark, sf_dir).join(labels, "doc_id").groupBy("method").agg(F.avg("quality").alias("value")).select("method", F.lit(20).alias("k"), F.lit("good").alias("metric"), "value")
    return measures.delta_vs_random(results).select("method", F.round("value", 6).alias("value"), F.round("delta", 6).alias("delta"))


@query(f"WITH {RANKED}, {SHIFT}, {TOP}, {_M} SELECT m.method, count(*) AS k, round(avg(quality), 6) AS good, round(avg(toxic), 6) AS toxic FROM m JOIN labels USING (doc_id) GROUP BY m.method")
def kept_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _labelled(three(spark, sf_dir), spark, sf_dir)


@query(f"WITH {RANKED}, bb AS (SELECT *, CASE WHEN pct < 0.2 THEN 'plain' WHEN pct >= 0.9 THEN 'chaotic' WHEN pct >= 0.4 AND pct < 0.8 THEN 'informative' ELSE 'between' END AS band FROM r) SELECT band, count(*) AS n, round(avg(x3), 6) AS distinct_words, round(avg(ln(1 + length(t)::DOUBLE)), 6) AS log_chars, list_sort(list(rank))[1:3]::VARCHAR AS first_ranks, list(doc_id ORDER BY rank)[1:3]::VARCHAR AS exemplars FROM bb GROUP BY band")
def region_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bands of the ranking: richness of their texts, and three exemplars, with their ranks."""
    from gradsift.functions.features import text_statistics

    band = F.when(F.col("pct") < 0.2, "plain").when(F.col("pct") >= 0.9, "chaotic").when((F.col("pct") >= 0.4) & (F.col("pct") < 0.8), "informative").otherwise("between")
    r = ranked(spark, sf_dir).withColumn("band", band)
    s = text_statistics(F.col("text"))
    shape = corpora.table(spark, sf_dir, "documents").select("doc_id", s["distinct"].alias("d"), s["log_chars"].alias("c"))
    out = r.join(shape, "doc_id").groupBy("band").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("d"), 6).alias("distinct_words"), F.round(F.avg("c"), 6).alias("log_chars"))
    # a group limit leaves three rows of each band and task before the exchange
    first = r.withColumn("_nth", F.row_number().over(Window.partitionBy("band").orderBy("rank"))).where("_nth <= 3")
    top = first.groupBy("band").agg(F.sort_array(F.collect_list(F.struct("rank", "doc_id"))).alias("x"))

    def shown(column: str) -> Column:
        return F.concat(F.lit("["), F.array_join(F.transform("x", lambda e: e[column].cast("string")), ", "), F.lit("]"))

    return out.join(top, "band").select("band", "n", "distinct_words", "log_chars", shown("rank").alias("first_ranks"), shown("doc_id").alias("exemplars"))


@query(f"WITH {RANKED}, {SHIFT} SELECT round(1 - count(*) FILTER (pct < 0.2 AND k.doc_id IS NOT NULL)::DOUBLE / count(*) FILTER (pct < 0.2), 6) AS plain_removed, round(1 - count(*) FILTER (pct >= 0.9 AND k.doc_id IS NOT NULL)::DOUBLE / count(*) FILTER (pct >= 0.9), 6) AS chaotic_removed FROM r LEFT JOIN k ON k.doc_id = r.doc_id")
def removed_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    marked = r.join(shifted(r).select("doc_id").withColumn("_kept", F.lit(1)), "doc_id", "left")

    def gone(band: Column) -> Column:
        return F.round(1 - F.count_if(band & F.col("_kept").isNotNull()) / F.count_if(band), 6)

    return marked.agg(gone(F.col("pct") < 0.2).alias("plain_removed"), gone(F.col("pct") >= 0.9).alias("chaotic_removed"))


@query(f"""WITH {RANKED}, {SHIFT}, {TOP}, {_M}, sc AS (SELECT m.method, source, lang, count(*) AS c FROM m JOIN documents USING (doc_id) GROUP BY ALL), q AS (SELECT method, source, sum(c) AS c FROM sc GROUP BY ALL),
    e AS (SELECT method, -sum(c / t * ln(c / t)) AS h, count(*) AS n FROM (SELECT *, sum(c) OVER (PARTITION BY method) AS t FROM q) GROUP BY method), g AS (SELECT method, count(DISTINCT lang) AS langs FROM sc GROUP BY method)
    SELECT method, n AS sources, langs, round(h, 6) AS source_entropy FROM e JOIN g USING (method)""")
def selection_diversity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = corpora.table(spark, sf_dir, "documents").select("doc_id", "source", "lang")
    cells = three(spark, sf_dir).join(docs, "doc_id").groupBy("method", "source", "lang").agg(F.count(F.lit(1)).alias("c"))
    total = cells.groupBy("method").agg(F.sum("c").alias("t"), F.count_distinct("lang").alias("langs"))
    by_source = cells.groupBy("method", "source").agg(F.sum("c").alias("c")).join(total, "method")
    p = F.col("c") / F.col("t")
    return by_source.groupBy("method", "langs").agg(F.count(F.lit(1)).alias("sources"), F.round(-F.sum(p * F.log(p)), 6).alias("source_entropy"))


@query(f"""WITH {RANKED}, l AS (SELECT score, quality FROM r JOIN labels USING (doc_id)), p AS (SELECT a.score AS x, b.score AS y FROM l a, l b WHERE a.quality = 1 AND b.quality = 0)
    SELECT round(avg(CASE WHEN x > y THEN 1.0 WHEN x = y THEN 0.5 ELSE 0.0 END), 6) AS auc, (SELECT count(*) FROM l WHERE quality = 1) AS positives, (SELECT count(*) FROM l WHERE quality = 0) AS negatives FROM p""")
def rater_auc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """AUC of the fixed rater against quality."""
    labels = corpora.table(spark, sf_dir, "labels").select("doc_id", "quality")
    return measures.auc(rated(spark, sf_dir).select("doc_id", "score").join(labels, "doc_id"), "score", "quality").withColumn("auc", F.round("auc", 6))


@query("SELECT 38400::BIGINT AS rater_visits, (count(*) // 5 * 3)::BIGINT AS downstream_visits, round(38400 / (count(*) // 5 * 3)::DOUBLE, 6) AS share FROM documents")
def rater_overhead(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = corpora.table(spark, sf_dir, "documents").agg(F.count(F.lit(1)).alias("n"))
    down = F.expr("n div 5 * 3")
    return n.select(F.lit(300 * 64 * 2).cast("long").alias("rater_visits"), down.alias("downstream_visits"), F.round(F.lit(300.0 * 64 * 2) / down, 6).alias("share"))


@query(f"WITH {RANKED}, {SHIFT}, {TOP} SELECT count(*) FILTER (k.doc_id IS NOT NULL AND top.doc_id IS NOT NULL) AS both, count(*) AS either, round(count(*) FILTER (k.doc_id IS NOT NULL AND top.doc_id IS NOT NULL)::DOUBLE / count(*), 6) AS jaccard FROM k FULL JOIN top ON k.doc_id = top.doc_id")
def selection_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = ranked(spark, sf_dir)
    return measures.selection_overlap(shifted(r), pruning.prune_top_k(r, fifth(r)), "doc_id").withColumn("jaccard", F.round("jaccard", 6))


@query()
def generated_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class shares of sequences drawn from a downstream model, against those of validation texts."""
    from gradsift.plans import downstream

    val = downstream.with_profiles(corpora.wanted(spark, sf_dir), "doc_id", "text", 32, []).orderBy("doc_id").toPandas()
    p = downstream.Profiles(list(val["cells"]), list(val["counts"]), 32)
    model, _ = downstream.train_bigram(p, 5, 64, 8.0, 42)
    drawn = np.bincount(downstream.generate(model, 64, 256).ravel(), minlength=32) / (64 * 256)
    real = np.bincount(p.cells % 32, p.shares, minlength=32) / max(1, len(p))
    return spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(zip(drawn, real, strict=True))], "class int, generated double, held_out double")


@query()
def exp_dynamics_trained(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Loss and gradient norm of all pool documents across the ranking, while a proxy trains on the pool."""
    from gradsift.plans import downstream, experiments

    ranks, pool = experiments.ranked_pool(spark, sf_dir), corpora.train_pool(spark, sf_dir).select("doc_id", "text")
    everything = ranks.select(F.lit("pool").alias("method"), "doc_id")
    models = [np.zeros((32, 32))]
    models += [m["pool"][1] for _, m in downstream.train_epochs(everything, pool, 32, 5, 64, 8.0, 42)]
    return measures.dynamics_by_range(downstream.traces(pool, models, 32), ranks, "doc_id")
