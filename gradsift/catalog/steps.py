"""Single steps of the meta-gradient method, exact, over line items and document bigrams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.catalog.fragments import ROWS, lin
from gradsift.catalog.registry import query
from gradsift.functions.features import bigram_counts as count_bigrams
from gradsift.functions.features import hashed_word_bigrams, raster_features
from gradsift.functions.hashing import hash32, hash_uniform
from gradsift.operators import meta, proxies, rating
from gradsift.operators.measures import selection_gain as gain
from gradsift.sources.corpora import raster_corpus, row_corpus, table

THETA, HAT = (0.5, 0.2, -0.1), (0.45, 0.25, -0.05)
MU = (0.4, -0.3, 0.2, 0.1)
GROUP = (0.3, -0.2, 0.1, 0.5, -0.4, 0.2, 0.05)
HIDDEN, HIDDEN_B, OUT, OUT_B = ((0.3, -0.2, 0.1, 0.5, -0.4, 0.2), (-0.5, 0.4, 0.2, -0.1, 0.3, 0.6)), (0.1, -0.1), (0.8, -0.6), 0.05
D = 3


def split_rows(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Training rows in hashed batches of about 64, and validation rows."""
    rows = row_corpus(spark, sf_dir)
    val = hash_uniform("sample_id", 7) < 0.1
    train = rows.where(~val)
    n = max(1, -(-train.count() // 64))
    return train.withColumn("batch_id", hash32("sample_id", 42) % n), rows.where(val)


def weighted(spark: SparkSession, sf_dir: str, group: tuple[float, ...] | None = GROUP) -> DataFrame:
    return meta.weigh(split_rows(spark, sf_dir)[0], MU, D, group)


def numbers(spark: SparkSession, values: list[float]) -> DataFrame:
    return spark.createDataFrame([(j, round(float(v), 6)) for j, v in enumerate(values)], "j int, value double")


def _list(exprs: list[str], source: str) -> str:
    return " UNION ALL ".join(f"SELECT {j} AS j, round({e}, 6) AS value FROM {source}" for j, e in enumerate(exprs))


_DESC = "d AS (SELECT batch_id, " + ", ".join(f"avg(a{i}) AS m{i}" for i in (1, 2, 3)) + ", " + ", ".join(f"var_pop(a{i}) AS v{i}" for i in (1, 2, 3)) + " FROM t GROUP BY batch_id)"
_SOFT = f"e AS (SELECT *, {lin(MU[:3])} + {MU[3]}::DOUBLE AS s FROM t), ex AS (SELECT *, exp(s - max(s) OVER (PARTITION BY batch_id)) AS q FROM e), iw AS (SELECT *, q / sum(q) OVER (PARTITION BY batch_id) AS iw FROM ex)"
_NAMES = ("m1", "m2", "m3", "v1", "v2", "v3")
_Z = " + ".join(f"{n} * ({g}::DOUBLE)" for n, g in zip(_NAMES, GROUP, strict=False)) + f" + {GROUP[6]}::DOUBLE"
WEIGHTED = f"{ROWS}, {_DESC}, {_SOFT}, g AS (SELECT batch_id, 1 / (1 + exp(-({_Z}))) AS bw FROM d), w AS (SELECT iw.*, bw, iw * bw AS w FROM iw JOIN g USING (batch_id))"


def res(theta) -> str:
    return f"({lin(theta)} - y)"


@query(f"WITH {ROWS}, {_SOFT} SELECT sample_id, round(iw, 6) AS inst_weight FROM iw")
def batch_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weighted(spark, sf_dir, None).select("sample_id", F.round("inst_weight", 6).alias("inst_weight"))


@query(f"WITH {ROWS}, {_DESC} SELECT batch_id, " + ", ".join(f"round({n}, 8) AS {n}" for n in _NAMES) + " FROM d")
def batch_descriptor(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = rating.batch_descriptor(split_rows(spark, sf_dir)[0], "features", D)
    return d.select("batch_id", *(F.round(F.col("descriptor")[i], 8).alias(n) for i, n in enumerate(_NAMES)))


_TWO = f"{OUT_B}::DOUBLE" + "".join(
    f" + tanh({b}::DOUBLE" + "".join(f" + {n} * ({x}::DOUBLE)" for n, x in zip(_NAMES, row, strict=True)) + f") * ({v}::DOUBLE)"
    for row, b, v in zip(HIDDEN, HIDDEN_B, OUT, strict=True)
)


@query(f"WITH {ROWS}, {_DESC} SELECT batch_id, round(1 / (1 + exp(-({_TWO}))), 6) AS batch_weight FROM d")
def group_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = rating.batch_descriptor(split_rows(spark, sf_dir)[0], "features", D)
    return rating.group_weight(d, HIDDEN, HIDDEN_B, OUT, OUT_B).select("batch_id", F.round("batch_weight", 6).alias("batch_weight"))


@query(f"WITH {WEIGHTED} SELECT sample_id, round(w, 6) AS weight FROM w")
def multi_granularity_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weighted(spark, sf_dir).select("sample_id", F.round("weight", 6).alias("weight"))


@query(f"WITH {ROWS}, {_SOFT} SELECT sample_id, round(iw, 6) AS weight FROM iw")
def instance_only_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rating.combine_weights(weighted(spark, sf_dir, None), None).select("sample_id", F.round("weight", 6).alias("weight"))


_GAP = f"(0.5 * {res(THETA)} * {res(THETA)} - 0.5 * {res(HAT)} * {res(HAT)})"
_LOSS = f"(0.5 * {res(THETA)} * {res(THETA)})"


def _gradients(mult: str) -> str:
    return f"""{WEIGHTED}, x AS (SELECT *, {mult} AS mu FROM w),
        mm AS (SELECT *, sum(iw * mu) OVER (PARTITION BY batch_id) AS mean_mult FROM x),
        gr AS (SELECT batch_id, any_value(mean_mult) AS mean_mult, any_value(bw) AS bw, sum(bw * iw * (mu - mean_mult) * a1) AS g0,
                      sum(bw * iw * (mu - mean_mult) * a2) AS g1, sum(bw * iw * (mu - mean_mult) * a3) AS g2, sum(bw * iw * (mu - mean_mult)) AS gb FROM mm GROUP BY batch_id)"""


@query(f"WITH {_gradients(_GAP)} SELECT batch_id, round(mean_mult, 6) AS mean_mult, round(bw, 6) AS batch_weight, round(g0, 6) + 0 AS g0, round(g1, 6) + 0 AS g1, round(g2, 6) + 0 AS g2, abs(gb) < 1e-9 AS sums_to_zero FROM gr")
def rater_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = meta.rater_gradient(meta.multipliers(weighted(spark, sf_dir), THETA, HAT), D)
    return g.select("batch_id", *(F.round(c, 6).alias(c) for c in ("mean_mult", "batch_weight", "g0", "g1", "g2")), (F.abs("g_bias") < 1e-9).alias("sums_to_zero"))


def _stepped(mult: str, alpha: float) -> str:
    exprs = [f"{MU[i]}::DOUBLE - {alpha}::DOUBLE * avg(g{i})" for i in range(3)] + [f"{MU[3]}::DOUBLE - {alpha}::DOUBLE * avg(gb)"]
    return f"WITH {_gradients(mult)} {_list(exprs, 'gr')}"


@query(_stepped(_GAP, 2.0))
def rater_step_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return numbers(spark, meta.rater_step(meta.multipliers(weighted(spark, sf_dir), THETA, HAT), MU, D, 2.0))


@query(_stepped(_LOSS, 2.0))
def rater_step_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    return numbers(spark, meta.rater_step(meta.multipliers(weighted(spark, sf_dir), THETA, None, "loss"), MU, D, 2.0))


def _uniform_steps(n: int, rate: float) -> str:
    out = [f"p0 AS (SELECT {', '.join(f'{t}::DOUBLE AS t{i + 1}' for i, t in enumerate((0.0, 0.0, 0.0)))})"]
    for k in range(1, n + 1):
        r = "(a1 * t1 + a2 * t2 + a3 * t3 - y)"
        out.append(f"p{k} AS (SELECT " + ", ".join(f"any_value(t{i}) - {rate}::DOUBLE * avg({r} * a{i}) AS t{i}" for i in (1, 2, 3)) + f" FROM t, p{k - 1})")
    return ", ".join(out)


@query(f"WITH {ROWS}, {_uniform_steps(3, 0.5)} " + " UNION ALL ".join(f"SELECT {k} AS step, {i - 1} AS j, round(t{i}, 6) AS value FROM p{k}" for k in range(4) for i in (1, 2, 3)))
def warmup_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    steps = meta.warm_up(split_rows(spark, sf_dir)[0], (0.0, 0.0, 0.0), 3, 0.5)
    return spark.createDataFrame([(k, j, round(v, 6)) for k, t in enumerate(steps) for j, v in enumerate(t)], "step int, j int, value double")


@query(f"WITH {WEIGHTED}, o AS (SELECT * FROM w WHERE batch_id = 0), p AS (SELECT " + ", ".join(f"sum(w * {res(THETA)} * a{i}) AS g{i}" for i in (1, 2, 3)) + " FROM o), q AS (SELECT " + ", ".join(f"avg({res(THETA)} * a{i}) AS h{i}" for i in (1, 2, 3)) + " FROM v WHERE val), pq AS (SELECT * FROM p, q) " + _list([f"{THETA[i]}::DOUBLE - 0.5::DOUBLE * (g{i + 1} + h{i + 1})" for i in range(3)], "pq"))
def joint_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, val = split_rows(spark, sf_dir)
    return numbers(spark, meta.joint_step(weighted(spark, sf_dir).where("batch_id = 0"), val, THETA, 0.5))


@query(f"WITH {WEIGHTED}, o AS (SELECT * FROM w WHERE batch_id = 0), p AS (SELECT " + ", ".join(f"sum(w * {res(HAT)} * a{i}) AS g{i}" for i in (1, 2, 3)) + " FROM o) " + _list([f"{HAT[i]}::DOUBLE - 0.5::DOUBLE * g{i + 1}" for i in range(3)], "p"))
def reference_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    return numbers(spark, meta.reference_step(weighted(spark, sf_dir).where("batch_id = 0"), HAT, 0.5))


def _weighted_steps(n: int, rate: float) -> str:
    out = ["c AS (SELECT *, w / sum(w) OVER () AS nw FROM w)", "p0 AS (SELECT 0::DOUBLE AS t1, 0::DOUBLE AS t2, 0::DOUBLE AS t3)"]
    for k in range(1, n + 1):
        r = "(a1 * t1 + a2 * t2 + a3 * t3 - y)"
        out.append(f"p{k} AS (SELECT " + ", ".join(f"any_value(t{i}) - {rate}::DOUBLE * sum(nw * {r} * a{i}) AS t{i}" for i in (1, 2, 3)) + f" FROM c, p{k - 1})")
    return ", ".join(out)


@query(f"WITH {WEIGHTED}, {_weighted_steps(3, 0.5)} " + _list(["t1", "t2", "t3"], "p3"))
def weighted_fit_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three steps of the inner problem over all rows, weights scaled to sum to 1."""
    w = weighted(spark, sf_dir)
    total = w.agg(F.sum("weight")).first()[0]
    scaled, theta = w.withColumn("weight", F.col("weight") / F.lit(total)), [0.0, 0.0, 0.0]
    for _ in range(3):
        theta = meta.reference_step(scaled, theta, 0.5)
    return numbers(spark, theta)


@query(f"WITH {WEIGHTED} SELECT batch_id, " + ", ".join(f"round(avg(w * {res(THETA)} * a{i}) * 1000, 6) AS g{i}" for i in (1, 2, 3)) + " FROM w GROUP BY batch_id")
def batch_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Thousandths of the minibatches' mean weighted gradients."""
    r = proxies.linear_residual(F.col("features"), F.col("target"), THETA)
    return weighted(spark, sf_dir).groupBy("batch_id").agg(*(F.round(F.avg(F.col("weight") * r * F.col("features")[i]) * 1000, 6).alias(f"g{i + 1}") for i in range(3)))


@query(f"WITH {ROWS}, {_uniform_steps(3, 0.5)} " + " UNION ALL ".join(f"SELECT {k} AS step, round(avg(0.5 * (a1 * t1 + a2 * t2 + a3 * t3 - y) * (a1 * t1 + a2 * t2 + a3 * t3 - y)), 6) AS val_loss FROM v, p{k} WHERE val" for k in range(4)))
def validation_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, val = split_rows(spark, sf_dir)
    steps = meta.warm_up(train, (0.0, 0.0, 0.0), 3, 0.5)
    # one scan for all steps' parameters
    loss = [F.avg(proxies.linear_loss(F.col("features"), F.col("target"), t)).alias(f"s{k}") for k, t in enumerate(steps)]
    wide = val.agg(*loss)
    return wide.select(F.explode(F.array(*(F.struct(F.lit(k).alias("step"), F.round(f"s{k}", 6).alias("val_loss")) for k in range(len(steps))))).alias("x")).select("x.*")


@query(f"WITH {ROWS} SELECT sample_id, round(0.5 * {res(THETA)} * {res(THETA)}, 6) AS loss FROM l")
def linear_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    return row_corpus(spark, sf_dir).select("sample_id", F.round(proxies.linear_loss(F.col("features"), F.col("target"), THETA), 6).alias("loss"))


@query(f"WITH {ROWS} SELECT sample_id, " + ", ".join(f"round({res(THETA)} * a{i}, 10) + 0 AS g{i}" for i in (1, 2, 3)) + " FROM l")
def linear_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = proxies.linear_gradient(F.col("features"), F.col("target"), THETA)
    return row_corpus(spark, sf_dir).withColumn("g", g).select("sample_id", *(F.round(F.col("g")[i], 10).alias(f"g{i + 1}") for i in range(3)))


_LZ = lin(THETA)


@query(f"WITH {ROWS}, k AS (SELECT *, CASE WHEN y > 0.4 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS c FROM l) SELECT sample_id, round(greatest({_LZ}, 0) - {_LZ} * c + ln(1 + exp(-abs({_LZ}))), 6) AS loss FROM k")
def logistic_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    label = F.when(F.col("target") > 0.4, F.lit(1.0)).otherwise(F.lit(0.0))
    return row_corpus(spark, sf_dir).select("sample_id", F.round(proxies.logistic_loss(F.col("features"), label, THETA), 6).alias("loss"))


@query(f"WITH {ROWS} SELECT round(avg({_LOSS}), 6) AS mean_loss, round(count(*) FILTER ({_LOSS} < 0.01)::DOUBLE / count(*), 6) AS share_under, round(3.0::DOUBLE / count(*), 9) AS params_per_sample, 'gap' AS rule FROM l")
def overparam_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = row_corpus(spark, sf_dir)
    out = meta.check_overparameterised(rows.withColumn("loss", proxies.linear_loss(F.col("features"), F.col("target"), THETA)), "loss", 0.01, D)
    return out.select(F.round("mean_loss", 6).alias("mean_loss"), F.round("share_under", 6).alias("share_under"), F.round("params_per_sample", 9).alias("params_per_sample"), "rule")


CANDIDATES = [(i, c) for i, c in enumerate((-2.0, -1.0, -0.5, 0.0, 0.5, 1.0, 2.0))]


@query(f"""WITH {ROWS}, k AS (SELECT unnest([{', '.join(str(i) for i, _ in CANDIDATES)}]) AS candidate, unnest([{', '.join(f'{c}::DOUBLE' for _, c in CANDIDATES)}]) AS c),
    i AS (SELECT candidate, c, sum(exp(c * a1) * a1 * y) / sum(exp(c * a1) * a1 * a1) AS theta FROM t, k GROUP BY candidate, c),
    o AS (SELECT candidate, c, theta, avg(0.5 * (theta * a1 - y) * (theta * a1 - y)) AS val_loss FROM v, i WHERE val GROUP BY candidate, c, theta)
    SELECT candidate, c, round(theta, 6) AS theta, round(val_loss, 6) AS val_loss, candidate = (SELECT candidate FROM o ORDER BY val_loss, candidate LIMIT 1) AS best FROM o""")
def bilevel_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    train, val = split_rows(spark, sf_dir)
    pick = [F.col("features")[0].alias("x"), F.col("target").alias("y")]
    grid = spark.createDataFrame(CANDIDATES, "candidate int, c double")
    out = meta.solve_bilevel_grid(train.select(*pick), val.select(*pick), grid)
    return out.select("candidate", "c", F.round("theta", 6).alias("theta"), F.round("val_loss", 6).alias("val_loss"), "best")


_BEST = "(sum(a1 * y) / sum(a1 * a1))"


@query(f"""WITH {ROWS}, a AS (SELECT {_BEST} AS th FROM t WHERE a2 >= 0.5), b AS (SELECT {_BEST} AS th FROM t),
    x AS (SELECT avg(0.5 * (th * a1 - y) * (th * a1 - y)) AS subset FROM v, a WHERE val), z AS (SELECT avg(0.5 * (th * a1 - y) * (th * a1 - y)) AS whole FROM v, b WHERE val)
    SELECT round(subset, 6) AS subset, round(whole, 6) AS whole, round(whole - subset, 6) AS gap, whole - subset >= -0.001 AS holds FROM x, z""")
def selection_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A one-feature model of half of the rows against that of all: is it as good on validation rows?"""
    train, val = split_rows(spark, sf_dir)
    x, y = F.col("features")[0], F.col("target")

    def value(rows: DataFrame) -> DataFrame:
        fit = rows.agg((F.sum(x * y) / F.sum(x * x)).alias("th"))
        return val.crossJoin(F.broadcast(fit)).agg(F.avg(F.lit(0.5) * (F.col("th") * x - y) * (F.col("th") * x - y)).alias("value"))

    out = gain(value(train.where(F.col("features")[1] >= 0.5)), value(train), tolerance=0.001)
    return out.select(*(F.round(c, 6).alias(c) for c in ("subset", "whole", "gap")), "holds")


# the autoregressive proxy

VOCAB = 32


def class_sql(ch: str) -> str:
    c = f"unicode({ch})"
    return f"CASE WHEN {c} BETWEEN 97 AND 122 THEN {c} - 97 WHEN {c} BETWEEN 65 AND 90 THEN 26 WHEN {c} BETWEEN 48 AND 57 THEN 27 WHEN {c} = 32 THEN 28 WHEN {c} = 10 THEN 29 WHEN {c} > 127 THEN 30 ELSE 31 END"


COUNTS = f"""p AS (SELECT doc_id, text, unnest(range(1, length(text))) AS i FROM documents),
    k AS (SELECT doc_id, {class_sql('substr(text, i, 1)')} AS a, {class_sql('substr(text, i + 1, 1)')} AS b FROM p),
    c AS (SELECT doc_id, a, b, count(*) AS n FROM k GROUP BY doc_id, a, b)"""
LOGITS = "lg AS (SELECT a, b, 0.1::DOUBLE * ((a * 7 + b * 3) % 11) AS value FROM (SELECT unnest(range(0, 32)) AS a), (SELECT unnest(range(0, 32)) AS b)), ls AS (SELECT a, ln(sum(exp(value))) AS lse FROM lg GROUP BY a)"


def logits(spark: SparkSession) -> DataFrame:
    a = spark.range(VOCAB).select(F.col("id").cast("int").alias("a"))
    b = spark.range(VOCAB).select(F.col("id").cast("int").alias("b"))
    return a.crossJoin(b).withColumn("value", F.lit(0.1) * ((F.col("a") * 7 + F.col("b") * 3) % 11))


def doc_bigrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_bigrams(table(spark, sf_dir, "documents"), "doc_id", "text", VOCAB)


@query(f"WITH {COUNTS} SELECT doc_id, a::INT AS a, b::INT AS b, n FROM c")
def bigram_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return doc_bigrams(spark, sf_dir)


@query("""WITH w AS (SELECT doc_id, list_filter(string_split_regex(lower(text), '[ \\n]'), lambda x: x <> '') AS ws FROM documents),
    k AS (SELECT doc_id, list_transform(ws, lambda x: ('0x' || substr(md5(x), 1, 8))::BIGINT % 32) AS c FROM w),
    p AS (SELECT doc_id, c, unnest(range(1, len(c))) AS i FROM k) SELECT doc_id, c[i]::INT AS a, c[i + 1]::INT AS b, count(*) AS n FROM p GROUP BY ALL""")
def word_bigram_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Transitions between words hashed to 32 classes, the other vocabulary of the autoregressive proxy."""
    return hashed_word_bigrams(table(spark, sf_dir, "documents"), "doc_id", "text", VOCAB)


@query(f"WITH {COUNTS}, {LOGITS} SELECT doc_id, sum(n)::BIGINT AS n, round(sum(n * (lse - value)) / sum(n), 6) AS loss FROM c JOIN lg USING (a, b) JOIN ls USING (a) GROUP BY doc_id")
def bigram_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    return proxies.bigram_loss(doc_bigrams(spark, sf_dir), logits(spark), "doc_id").withColumn("loss", F.round("loss", 6))


@query(f"""WITH {COUNTS}, {LOGITS}, s AS (SELECT doc_id, sum(n) AS t FROM c GROUP BY doc_id), m AS (SELECT a, b, sum(n / t) / (SELECT count(*) FROM s) AS x FROM c JOIN s USING (doc_id) GROUP BY a, b),
    rw AS (SELECT a, sum(x) AS r FROM m GROUP BY a) SELECT a::INT AS a, b::INT AS b, round((r * exp(value - lse) - coalesce(x, 0)) * 1000, 6) AS grad1000 FROM lg JOIN ls USING (a) JOIN rw USING (a) LEFT JOIN m USING (a, b)""")
def bigram_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = proxies.bigram_gradient(doc_bigrams(spark, sf_dir), logits(spark), "doc_id")
    return g.select("a", "b", F.round(F.col("grad") * 1000, 6).alias("grad1000"))


# rasters


def _mean(cells: list[int]) -> str:
    return "(" + " + ".join(f"embedding[{c + 1}]::DOUBLE" for c in cells) + f") / {len(cells)}::DOUBLE"


def _pool(to: int) -> list[str]:
    s = 8 // to
    return [_mean([(r * s + i) * 8 + c * s + j for i in range(s) for j in range(s)]) for r in range(to) for c in range(to)]


@query("SELECT vec_id AS sample_id, " + ", ".join(f"round({e}, 6) AS p{i}" for i, e in enumerate(_pool(1) + _pool(2) + _pool(4))) + " FROM embeddings")
def pyramid_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    levels = proxies.pyramid(F.col("pixels"))
    flat = raster_corpus(spark, sf_dir).select("sample_id", F.concat(levels[1], levels[2], levels[4]).alias("p"))
    return flat.select("sample_id", *(F.round(F.col("p")[i], 6).alias(f"p{i}") for i in range(21)))


def _scale(k: int, w: float) -> str:
    big, low, high = 2 * k, _pool(k), _pool(2 * k)
    terms = [f"pow({w}::DOUBLE * ({low[(r // 2) * k + c // 2]}) - ({high[r * big + c]}), 2)" for r in range(big) for c in range(big)]
    return "(" + " + ".join(terms) + f") / {len(terms)}::DOUBLE"


@query(f"SELECT vec_id AS sample_id, round(({_scale(1, 0.9)} + {_scale(2, 0.8)} + {_scale(4, 0.7)}) / 3 * 100, 6) AS loss100 FROM embeddings")
def scale_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    return raster_corpus(spark, sf_dir).select("sample_id", F.round(proxies.scale_loss(F.col("pixels"), (0.9, 0.8, 0.7)) * 100, 6).alias("loss100"))


@query("SELECT vec_id AS sample_id, " + ", ".join(f"round({e}, 6) AS f{i}" for i, e in enumerate(_pool(2))) + ", round(list_avg(embedding::DOUBLE[]), 6) AS f4, round(list_stddev_pop(embedding::DOUBLE[]), 6) AS f5 FROM embeddings")
def pooled_raster_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return raster_corpus(spark, sf_dir).withColumn("f", raster_features(F.col("pixels"))).select("sample_id", *(F.round(F.col("f")[i], 6).alias(f"f{i}") for i in range(6)))


@query()
def denoise_loss_by_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean loss and its spread over samples, for each noise level: it depends on the level."""
    rows = raster_corpus(spark, sf_dir)
    wide = rows.select(*(proxies.denoise_loss(F.col("pixels"), "sample_id", t).alias(f"t{t}") for t in range(5)))
    stats = wide.agg(*(F.struct(F.lit(t).alias("level"), F.avg(f"t{t}").alias("mean_loss"), F.stddev_pop(f"t{t}").alias("spread")).alias(f"s{t}") for t in range(5)))
    return stats.select(F.explode(F.array(*(F.col(f"s{t}") for t in range(5)))).alias("x")).select("x.*")
