"""Operators, functions and streams around the method, each over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.catalog.fragments import RANKED, RATER, SCORE, exact_sample, stats, u
from gradsift.catalog.registry import SQL, query
from gradsift.catalog.selection import SHIFTED, fifth, ranked
from gradsift.functions.udfs import mlp_score, register_linear, register_tables, second_moment
from gradsift.operators import pruning
from gradsift.operators.batching import split_of
from gradsift.plans.rater import FIXED_MLP
from gradsift.sources.corpora import number_within, table, text_corpus
from gradsift.streaming import streams

TOP = "t5 AS (SELECT doc_id FROM r WHERE rank <= (SELECT count(*) // 5 FROM r))"
SH = f"sh AS ({exact_sample(0.2, 0.6, 0.2, 'count(*) // 5')})"


def pair(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    r = ranked(spark, sf_dir)
    k = fifth(r)
    return pruning.prune_top_k(r, k).select("doc_id"), pruning.prune_shifted_gaussian(r, k, "doc_id", SHIFTED).select("doc_id")


@query("SELECT lang, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents WHERE source = 'src1' GROUP BY lang")
def scan_parquet_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").where("source = 'src1'").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@query("SELECT doc_id FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 100 AND 5000 AND source IS NOT DISTINCT FROM 'src3' AND regexp_matches(text, '[0-9]')")
def filter_predicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents")
    return d.where(F.col("lang").isin("en", "de") & F.col("n_chars").between(100, 5000) & F.col("source").eqNullSafe("src3") & F.col("text").rlike("[0-9]")).select("doc_id")


@query("SELECT d.doc_id, d.lang, l.quality, l.toxic FROM documents d JOIN labels l USING (doc_id)")
def join_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id")


@query("SELECT doc_id, CASE lang WHEN 'en' THEN 1.0::DOUBLE WHEN 'fr' THEN 0.5::DOUBLE END AS prior FROM documents WHERE lang IN ('en', 'fr')")
def join_broadcast_params(spark: SparkSession, sf_dir: str) -> DataFrame:
    priors = spark.createDataFrame([("en", 1.0), ("fr", 0.5)], "lang string, prior double")
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(F.broadcast(priors), "lang").select("doc_id", "prior")


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity)::DOUBLE, 2) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_sortmerge(spark: SparkSession, sf_dir: str) -> DataFrame:
    l, o = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders").hint("merge")
    return l.join(o, l["l_orderkey"] == o["o_orderkey"]).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity").cast("double"), 2).alias("qty"))


@query(f"WITH {RANKED}, {SH} SELECT doc_id, lang FROM documents SEMI JOIN sh USING (doc_id)")
def semi_selected(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(pair(spark, sf_dir)[1], "doc_id", "left_semi")


@query(f"WITH {RANKED}, {SH} SELECT doc_id FROM documents ANTI JOIN sh USING (doc_id)")
def anti_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id").join(pair(spark, sf_dir)[1], "doc_id", "left_anti")


@query(f"WITH {RANKED}, {TOP}, {SH} SELECT coalesce(t5.doc_id, sh.doc_id) AS doc_id, t5.doc_id IS NOT NULL AS in_top, sh.doc_id IS NOT NULL AS in_shifted FROM t5 FULL JOIN sh ON t5.doc_id = sh.doc_id")
def outer_selections(spark: SparkSession, sf_dir: str) -> DataFrame:
    top, sh = pair(spark, sf_dir)
    both = top.withColumn("a", F.lit(True)).join(sh.withColumn("b", F.lit(True)), "doc_id", "full")
    return both.select("doc_id", F.col("a").isNotNull().alias("in_top"), F.col("b").isNotNull().alias("in_shifted"))


@query("SELECT r_name, m AS mean FROM region, (SELECT unnest([0.4::DOUBLE, 0.5::DOUBLE, 0.6::DOUBLE]) AS m)")
def cross_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    grid = spark.createDataFrame([(0.4,), (0.5,), (0.6,)], "mean double")
    return table(spark, sf_dir, "region").select("r_name").crossJoin(F.broadcast(grid))


BANDS = ((0, 0.0, 0.2), (1, 0.2, 0.4), (2, 0.4, 0.8), (3, 0.8, 1.01))


@query(f"WITH {RANKED}, bands AS (SELECT * FROM (VALUES " + ", ".join(f"({b}, {lo}::DOUBLE, {hi}::DOUBLE)" for b, lo, hi in BANDS) + ") AS v(band, lo, hi)) SELECT doc_id, band FROM r JOIN bands ON pct >= lo AND pct < hi")
def range_join_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    bands = spark.createDataFrame(BANDS, "band int, lo double, hi double")
    return ranked(spark, sf_dir).join(F.broadcast(bands), (F.col("pct") >= F.col("lo")) & (F.col("pct") < F.col("hi"))).select("doc_id", "band")


@query("WITH c AS (SELECT ts AS cat, event_id AS checkpoint, user_id FROM events WHERE event_type = 'purchase') SELECT e.event_id, c.checkpoint FROM (SELECT * FROM events WHERE event_type <> 'purchase') e ASOF LEFT JOIN (SELECT user_id, cat, max(checkpoint) AS checkpoint FROM c GROUP BY user_id, cat) c ON e.user_id = c.user_id AND e.ts >= c.cat")
def asof_checkpoint(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event's latest checkpoint of its user: a union and a running last value, one exchange."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts")
    mark = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    # at equal times the checkpoint comes first, the one with the largest id last among them
    order = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") != "purchase", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("checkpoint", F.last(mark, ignorenulls=True).over(order)).where("event_type <> 'purchase'").select("event_id", "checkpoint")


@query("SELECT a.event_id AS error_id, b.event_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'error'")
def interval_join_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events within an hour of an error: equal on user and hour bucket, so each side is exchanged once."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts")
    hour = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600)
    errors = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("ts").alias("at"), F.explode(F.array(hour, hour + 1)).alias("h"))
    others = e.select("event_id", "user_id", "ts", hour.alias("h"))
    return errors.join(others, ["user_id", "h"]).where((F.col("ts") > F.col("at")) & (F.col("ts") <= F.col("at") + F.expr("INTERVAL 1 HOUR"))).select("error_id", "event_id")


@query("SELECT a.vec_id, b.vec_id AS probe, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a, (SELECT * FROM embeddings WHERE vec_id < 5) b WHERE list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) > 0.3")
def nl_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All vectors against a stated handful of probes."""
    from gradsift.functions.networks import inner
    from gradsift.sources.corpora import raster_corpus

    rows = raster_corpus(spark, sf_dir).select("sample_id", "pixels")
    probes = rows.where("sample_id < 5").select(F.col("sample_id").alias("probe"), F.col("pixels").alias("q"))
    c = inner(F.col("pixels"), F.col("q"))
    return rows.crossJoin(F.broadcast(probes)).where(c > 0.3).select(F.col("sample_id").alias("vec_id"), "probe", F.round(c, 6).alias("cosine"))


@query("SELECT a.vec_id, b.vec_id AS probe, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a, (SELECT * FROM embeddings WHERE vec_id % 20 = 0) b WHERE list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) > 0.3")
def nl_cosine_twentieth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All vectors against all whose id is divisible by 20, which meet them in blocks of about 256."""
    from gradsift.functions.hashing import hash32
    from gradsift.functions.networks import inner
    from gradsift.sources.corpora import raster_corpus

    rows = raster_corpus(spark, sf_dir).select("sample_id", "pixels")
    probes = rows.where("sample_id % 20 = 0")
    blocks = max(1, -(-probes.count() // 256))
    one = F.struct(F.col("sample_id").alias("probe"), F.col("pixels").alias("q"))
    blocked = probes.groupBy((hash32("sample_id", 3) % blocks).alias("block")).agg(F.collect_list(one).alias("held")).select("held")
    pairs = rows.crossJoin(blocked).select("sample_id", "pixels", F.inline("held"))
    c = inner(F.col("pixels"), F.col("q"))
    return pairs.where(c > 0.3).select(F.col("sample_id").alias("vec_id"), "probe", F.round(c, 6).alias("cosine"))


_AGG = "count(*) AS n, sum(n_chars)::BIGINT AS chars"


def _sums(grouped) -> DataFrame:
    return grouped.agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@query(f"SELECT lang, source, {_AGG} FROM documents GROUP BY ROLLUP (lang, source)")
def agg_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sums(table(spark, sf_dir, "documents").rollup("lang", "source"))


@query(f"SELECT lang, source, {_AGG} FROM documents GROUP BY CUBE (lang, source)")
def agg_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sums(table(spark, sf_dir, "documents").cube("lang", "source"))


@query(f"SELECT lang, source, {_AGG} FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents")
    return _sums(d.groupingSets([[d["lang"]], [d["source"]], []], d["lang"], d["source"]))


@query("SELECT event_type, count(*) FILTER (extract(dow FROM ts) = 0) AS sun, count(*) FILTER (extract(dow FROM ts) = 1) AS mon, count(*) FILTER (extract(dow FROM ts) = 2) AS tue FROM events GROUP BY event_type")
def pivot_metrics(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").withColumn("d", F.dayofweek("ts"))
    p = e.groupBy("event_type").pivot("d", [1, 2, 3]).agg(F.count(F.lit(1)))
    return p.select("event_type", *(F.coalesce(F.col(c), F.lit(0)).alias(n) for c, n in (("1", "sun"), ("2", "mon"), ("3", "tue"))))


@query("SELECT source, count(*) FILTER (lang = 'en') AS english, max(n_chars) FILTER (lang <> 'en') AS longest_other, count(DISTINCT lang) AS langs, arg_max(doc_id, n_chars * 1000000 + doc_id) AS longest, round(var_pop(n_chars), 3) AS var FROM documents GROUP BY source")
def agg_filtered(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").groupBy("source").agg(
        F.count_if(F.col("lang") == "en").alias("english"), F.max(F.when(F.col("lang") != "en", F.col("n_chars"))).alias("longest_other"),
        F.count_distinct("lang").alias("langs"), F.max_by("doc_id", F.col("n_chars") * 1000000 + F.col("doc_id")).alias("longest"), F.round(F.var_pop("n_chars"), 3).alias("var"),
    )


@query("SELECT doc_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 6) AS pr, ntile(4) OVER w AS nt, round(cume_dist() OVER v, 6) AS cd FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars, doc_id), v AS (PARTITION BY source ORDER BY n_chars)")
def win_ranking(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, v = Window.partitionBy("source").orderBy("n_chars", "doc_id"), Window.partitionBy("source").orderBy("n_chars")
    return table(spark, sf_dir, "documents").select(
        "doc_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"),
        F.round(F.percent_rank().over(v), 6).alias("pr"), F.ntile(4).over(w).cast("long").alias("nt"), F.round(F.cume_dist().over(v), 6).alias("cd"),
    )


@query("SELECT event_id, round(value - lag(value) OVER w, 6) AS delta, round(lead(value) OVER w, 6) AS following FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select("event_id", F.round(F.col("value") - F.lag("value").over(w), 6).alias("delta"), F.round(F.lead("value").over(w), 6).alias("following"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS moving FROM events")
def win_rows_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return table(spark, sf_dir, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("moving"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS hour_events FROM events")
def win_range_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").withColumn("s", F.unix_timestamp(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("hour_events"))


@query("SELECT event_id, first_value(event_id) OVER w AS first, last_value(event_id) OVER w AS last, nth_value(event_id, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf_dir, "events").select("event_id", F.first("event_id").over(w).alias("first"), F.last("event_id").over(w).alias("last"), F.nth_value("event_id", 2).over(w).alias("second"))


@query("SELECT source, doc_id, nth FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS nth FROM documents) WHERE nth <= 3")
def topk_per_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spark cuts each task's rows of a group to k before the exchange."""
    w = Window.partitionBy("source").orderBy(F.col("n_chars").desc(), "doc_id")
    return table(spark, sf_dir, "documents").select("source", "doc_id", F.row_number().over(w).alias("nth")).where("nth <= 3").withColumn("nth", F.col("nth").cast("long"))


@query(f"WITH {RANKED}, {TOP}, {SH} SELECT doc_id FROM t5 UNION SELECT doc_id FROM sh")
def set_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = pair(spark, sf_dir)
    return a.unionByName(b).distinct()


@query(f"WITH {RANKED}, {TOP}, {SH} SELECT doc_id FROM t5 INTERSECT SELECT doc_id FROM sh")
def set_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = pair(spark, sf_dir)
    return a.intersect(b)


@query(f"WITH {RANKED}, {TOP}, {SH} SELECT doc_id FROM t5 EXCEPT SELECT doc_id FROM sh")
def set_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    a, b = pair(spark, sf_dir)
    return a.subtract(b)


@query("SELECT p_partkey, upper(p_name) AS up, length(p_name) AS len, split_part(p_name, ' ', 1) AS head, substr(p_name, 2, 3) AS sub, md5(p_name) AS md5, sha256(p_name) AS sha, levenshtein(p_name, p_brand) AS lev, instr(p_name, 'a') AS pos, concat_ws('/', p_brand, p_type) AS cat, regexp_replace(p_name, '[aeiou]', '', 'g') AS bare, len(regexp_extract_all(p_name, '[a-z]+')) AS words FROM part")
def fn_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("p_name")
    return table(spark, sf_dir, "part").select(
        "p_partkey", F.upper(n).alias("up"), F.length(n).cast("long").alias("len"), F.split_part(n, F.lit(" "), F.lit(1)).alias("head"), F.substring(n, 2, 3).alias("sub"),
        F.md5(n.cast("binary")).alias("md5"), F.sha2(n, 256).alias("sha"), F.levenshtein(n, "p_brand").cast("long").alias("lev"), F.instr(n, "a").cast("long").alias("pos"),
        F.concat_ws("/", "p_brand", "p_type").alias("cat"), F.regexp_replace(n, "[aeiou]", "").alias("bare"), F.size(F.regexp_extract_all(n, F.lit("[a-z]+"), F.lit(0))).cast("long").alias("words"),
    )


@query("SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, strftime(o_orderdate + INTERVAL 10 DAY, '%Y-%m-%d') AS later, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS days, quarter(o_orderdate) AS quarter, dayofyear(o_orderdate) AS day FROM orders")
def fn_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select(
        "o_orderkey", F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month"), F.date_format(F.date_add(d.cast("date"), 10), "yyyy-MM-dd").alias("later"),
        F.datediff(d.cast("date"), F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.quarter(d).cast("long").alias("quarter"), F.dayofyear(d).cast("long").alias("day"),
    )


@query("SELECT event_id, round(exp(-abs(value) / 100), 6) AS e, round(ln(1 + abs(value)), 6) AS l, round(sqrt(abs(value)), 6) AS s, round(tanh(value / 100), 6) AS t, round(1 / (1 + exp(-value / 100)), 6) AS sig, greatest(value, 10) AS g, least(value, 10) AS m, floor(value)::BIGINT AS f FROM events")
def fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("value")
    return table(spark, sf_dir, "events").select(
        "event_id", F.round(F.exp(-F.abs(v) / 100), 6).alias("e"), F.round(F.log1p(F.abs(v)), 6).alias("l"), F.round(F.sqrt(F.abs(v)), 6).alias("s"), F.round(F.tanh(v / 100), 6).alias("t"),
        F.round(1 / (1 + F.exp(-v / 100)), 6).alias("sig"), F.greatest(v, F.lit(10.0)).alias("g"), F.least(v, F.lit(10.0)).alias("m"), F.floor(v).alias("f"),
    )


@query("SELECT vec_id, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)), 6) AS norm2, len(list_filter(embedding::DOUBLE[], lambda x: x > 0)) AS positive, round(list_max(embedding::DOUBLE[]), 6) AS top, round((list_sort(embedding::DOUBLE[]))[1], 6) AS low, round(list_sum((embedding::DOUBLE[])[1:8]), 6) AS head FROM embeddings")
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = F.transform("embedding", lambda x: x.cast("double"))
    add = lambda s, x: s + x
    return table(spark, sf_dir, "embeddings").select(
        "vec_id", F.round(F.aggregate(F.transform(a, lambda x: x * x), F.lit(0.0), add), 6).alias("norm2"), F.size(F.filter(a, lambda x: x > 0)).cast("long").alias("positive"),
        F.round(F.array_max(a), 6).alias("top"), F.round(F.array_sort(a)[0], 6).alias("low"), F.round(F.aggregate(F.slice(a, 1, 8), F.lit(0.0), add), 6).alias("head"),
    )


@query("SELECT source, cardinality(map_from_entries(list({k: lang, v: n}))) AS langs, max(n) FILTER (lang = 'en') AS english FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY ALL) GROUP BY source")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return m.select("source", F.size(F.map_keys("m")).cast("long").alias("langs"), F.try_element_at("m", F.lit("en")).alias("english"))


@query("SELECT page_id, regexp_extract(url, '^([a-z]+)://', 1) AS scheme, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages")
def fn_url(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", F.parse_url("url", F.lit("PROTOCOL")).alias("scheme"), F.parse_url("url", F.lit("HOST")).alias("host"))


@query(f"SELECT doc_id, CASE WHEN {u('doc_id', 7)} < 0.1 THEN 'val' WHEN {u('doc_id', 7)} < 0.2 THEN 'test' ELSE 'train' END AS split FROM documents")
def hash_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", split_of("doc_id").alias("split"))


@query(f"SELECT doc_id, lang FROM documents WHERE {u('doc_id', 11)} < CASE lang WHEN 'en' THEN 0.1 WHEN 'fr' THEN 0.4 ELSE 0.5 END")
def stratified_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    from gradsift.functions.hashing import hash_uniform

    share = F.when(F.col("lang") == "en", 0.1).when(F.col("lang") == "fr", 0.4).otherwise(0.5)
    return table(spark, sf_dir, "documents").where(hash_uniform("doc_id", 11) < share).select("doc_id", "lang")


@query(f"WITH {stats()}, s AS (SELECT *, {SCORE} AS score FROM f) SELECT lang, count(*) AS n, round(avg(score), 6) AS mean_score FROM s WHERE score > 0 GROUP BY lang")
def sql_end_to_end(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A temporary view and a SQL function, which the optimizer inlines."""
    text_corpus(spark, sf_dir).createOrReplaceTempView("gradsift_corpus")
    register_linear(spark, "gradsift_rate", RATER)
    return spark.sql("SELECT lang, count(*) AS n, round(avg(gradsift_rate(features)), 6) AS mean_score FROM gradsift_corpus WHERE gradsift_rate(features) > 0 GROUP BY lang")


@query(SQL["rate_mlp"])
def udf_mlp_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The fixed network as a vectorised Python function: the way of networks too large for a plan."""
    return text_corpus(spark, sf_dir).select("doc_id", F.round(mlp_score(*FIXED_MLP)("features"), 6).alias("score"))


@query("SELECT event_type, round(avg(value * value), 4) AS second FROM events GROUP BY event_type")
def udf_second_moment(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.round(second_moment("value"), 4).alias("second"))


@query("WITH w AS (SELECT p_partkey, string_split(p_name, ' ') AS ws FROM part), p AS (SELECT p_partkey, ws, unnest(range(1, len(ws))) AS i FROM w) SELECT p_partkey, (i - 1)::INT AS pos, ws[i] || ' ' || ws[i + 1] AS gram FROM p")
def udtf_ngrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_tables(spark)
    table(spark, sf_dir, "part").select("p_partkey", "p_name").createOrReplaceTempView("gradsift_parts")
    return spark.sql("SELECT p_partkey, pos, gram FROM gradsift_parts, LATERAL explode_ngrams(p_name, 2)")


@query("SELECT doc_id, k::INT AS step, round(2.0::DOUBLE / (1 + 0.1::DOUBLE * k), 9) AS rate FROM (SELECT doc_id, unnest(range(0, (n_chars + 511) // 512)) AS k FROM documents)")
def udtf_unroll_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The learning rates of a pass over each document: a step for every window of 512 characters begun."""
    register_tables(spark)
    steps = F.expr("(n_chars + 511) DIV 512").alias("steps")
    table(spark, sf_dir, "documents").select("doc_id", steps).createOrReplaceTempView("gradsift_passes")
    return spark.sql("SELECT doc_id, step, round(rate, 9) AS rate FROM gradsift_passes, LATERAL unroll_steps(steps, 2.0D, 0.1D)")


@query("SELECT event_id, json_extract_string(props, '$.k')  AS k, len(json_keys(props)) AS n_keys FROM events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"), F.size(F.json_object_keys("props")).cast("long").alias("n_keys"))


@query("SELECT doc_id, row_number() OVER (PARTITION BY lang ORDER BY doc_id) AS nth FROM documents")
def number_within_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return number_within(table(spark, sf_dir, "documents").select("doc_id", "lang"), ["lang"], "doc_id").select("doc_id", "nth")


# streams, drained: the same rows as in batch

_WIN = "SELECT strftime({start}, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean_value FROM {source} GROUP BY 1, 2"


def _windows(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    out = streams.drain(streams.stream_window_loss(streams.events(spark, sf_dir), kind), "complete" if kind != "session" else "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n", F.round("mean_value", 6).alias("mean_value"))


@query(_WIN.format(start="date_trunc('day', ts)", source="events"))
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "tumbling")


@query(_WIN.format(start="ws", source="(SELECT *, time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '2000-01-01') - unnest([0, 12]) * INTERVAL 1 HOUR AS ws FROM events)"))
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "sliding")


@query("""WITH g AS (SELECT *, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY event_type ORDER BY ts, event_id)),
    s AS (SELECT *, sum(new) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS session FROM g)
    SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean_value FROM s GROUP BY event_type, session""")
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _windows(spark, sf_dir, "session")


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.drain(streams.stream_dedup(streams.events(spark, sf_dir), ["user_id", "event_type"], "60 days")).select("user_id", "event_type")


@query("SELECT event_id, round(0.02 * value - 1, 6) AS score FROM events")
def stream_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = streams.drain(streams.stream_rate(streams.events(spark, sf_dir), F.lit(0.02) * F.col("value") - 1))
    return out.select("event_id", F.round("score", 6).alias("score"))


CUTS = (10.0, 20.0, 30.0, 40.0, 50.0, 60.0, 70.0, 80.0, 90.0)
_BIN = " + ".join(f"(value >= {c})::INT" for c in CUTS)
_G = "CASE WHEN pct < 0.2 THEN 0::DOUBLE ELSE exp(-((pct - 0.6::DOUBLE) * (pct - 0.6::DOUBLE)) / 0.08::DOUBLE) END"


@query(f"WITH b AS (SELECT event_id, 1 - (({_BIN}) + 1) / 10::DOUBLE AS pct FROM events) SELECT event_id, round(pct, 6) + 0 AS pct FROM b WHERE {u('event_id', 42)} < least(1, 0.4::DOUBLE * ({_G}))")
def stream_select(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cuts of an earlier snapshot are fixed here; a row's inclusion depends on its id alone."""
    rated_stream = streams.stream_rate(streams.events(spark, sf_dir), F.col("value"))
    return streams.drain(streams.stream_select(rated_stream, list(CUTS), "event_id")).select("event_id", F.round("pct", 6).alias("pct"))


@query("SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON user_id = c_custkey")
def stream_static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    static = table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("user_id"), "c_mktsegment")
    return streams.drain(streams.stream_static_join(streams.events(spark, sf_dir), static, ["user_id"])).select("event_id", "c_mktsegment")


@query("SELECT a.event_id AS emitted_id, b.event_id AS reported_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'click'")
def stream_join_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = streams.events(spark, sf_dir)
    out = streams.drain(streams.stream_join_loss(e.where("event_type = 'view'"), streams.events(spark, sf_dir).where("event_type = 'click'"), "1 HOUR", "60 days"))
    return out.select("emitted_id", "reported_id")
