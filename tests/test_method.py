"""Worked examples, gradients, samplers and the engine's invariants."""

from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from gradsift.operators import measures, meta, pruning
from gradsift.operators.pruning import ShiftedGaussian, density, inclusion_scale, water_fill
from gradsift.operators.ranking import rank_corpus, select_smallest
from gradsift.operators.rating import batch_descriptor, combine_weights, softmax_in_batch
from gradsift.plans.downstream import Profiles, bigram_nll, generate
from gradsift.plans.rater import Rater, RaterConfig, average
from gradsift.plans.training import MetaConfig, TrainState, meta_step, run_steps, warm_up
from gradsift.schemas import SampleSpec, bind, validate_corpus


def scores(spark):
    rows = [(1, math.log(1)), (2, math.log(2)), (3, math.log(1))]
    return spark.createDataFrame([(i, s, 0) for i, s in rows], "id int, s double, batch_id int")


def test_softmax_in_batch_and_shift(spark):
    for add in (0.0, 1000.0):
        out = softmax_in_batch(scores(spark).withColumn("s", F.col("s") + add), "s").orderBy("id").collect()
        assert [r.inst_weight for r in out] == pytest.approx([0.25, 0.5, 0.25])


def test_product_weight(spark):
    soft = softmax_in_batch(scores(spark), "s")
    batches = spark.createDataFrame([(0, 0.5)], "batch_id int, batch_weight double")
    w = [r.weight for r in combine_weights(soft, batches).orderBy("id").collect()]
    assert w == pytest.approx([0.125, 0.25, 0.125]) and sum(w) == pytest.approx(0.5)


def test_batch_descriptor(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (0, [3.0, 4.0])], "batch_id int, f array<double>")
    assert batch_descriptor(df, "f", 2).first().descriptor == pytest.approx([2, 2, 1, 4])


def test_percentiles_topk_and_block(spark):
    df = spark.createDataFrame([(1, 9.0), (2, 7.0), (3, 7.0), (4, 5.0)], "id long, s double")
    r = rank_corpus(df, "s", "id")
    assert [(x.id, x["rank"], x.pct) for x in r.orderBy("rank").collect()] == [(1, 1, 0.0), (2, 2, 0.25), (3, 3, 0.5), (4, 4, 0.75)]
    ids = lambda d: {x.id for x in d.collect()}
    assert ids(pruning.prune_top_k(r, 2)) == {1, 2} == ids(pruning.prune_block(r, 0.0, 0.5))
    assert ids(pruning.prune_block(r, 0.25, 0.5)) == {2, 3}


def test_rank_with_many_ties_is_exact(spark):
    df = spark.range(5000).select("id", F.when(F.col("id") % 3 == 0, F.lit(1.0)).otherwise((F.col("id") % 50).cast("double")).alias("s"))
    got = [(r.id, r["rank"]) for r in rank_corpus(df, "s", "id").orderBy("rank").collect()]
    want = sorted(((r.id, r.s) for r in df.collect()), key=lambda x: (-x[1], x[0]))
    assert got == [(i, k + 1) for k, (i, _) in enumerate(want)]


def test_rank_ignores_partitions(spark):
    df = spark.range(500).select("id", F.sin(F.col("id").cast("double")).alias("s"))
    one = rank_corpus(df.repartition(1), "s", "id").select("id", "rank").collect()
    many = rank_corpus(df.repartition(40), "s", "id").select("id", "rank").collect()
    assert sorted(map(tuple, one)) == sorted(map(tuple, many))


def test_rank_plan_has_no_single_partition(spark):
    df = spark.range(2000).select("id", F.sin(F.col("id").cast("double")).alias("s"))
    plan = rank_corpus(df, "s", "id")._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in plan and "CartesianProduct" not in plan


def test_select_smallest(spark):
    df = spark.range(1000).select("id", (F.col("id") % 7).cast("double").alias("k"))
    want = sorted(((r.k, r.id) for r in df.collect()))[:333]
    assert sorted((r.k, r.id) for r in select_smallest(df, "k", 333, "id").collect()) == want
    assert select_smallest(df, "k", 0, "id").count() == 0
    with pytest.raises(ValueError):
        select_smallest(df, "k", 1001, "id")


def test_density_values(spark):
    df = spark.createDataFrame([(p,) for p in (0.1, 0.3, 0.5, 0.7, 0.9)], "pct double")
    out = pruning.gaussian_density(df, ShiftedGaussian()).orderBy("pct").collect()
    assert [r.g for r in out] == pytest.approx([0, 0.324652, 0.882497, 0.882497, 0.324652], abs=1e-6)
    assert [r.p for r in out] == pytest.approx([0, 0.134471, 0.365529, 0.365529, 0.134471], abs=1e-6)


@pytest.fixture(scope="module")
def ranked(spark):
    return rank_corpus(spark.range(4000).select("id", F.sin(F.col("id").cast("double")).alias("s")), "s", "id").cache()


def test_samplers(spark, ranked):
    cfg = ShiftedGaussian()
    small = {r.id for r in pruning.prune_shifted_gaussian(ranked, 400, "id", cfg).collect()}
    large = {r.id for r in pruning.prune_shifted_gaussian(ranked, 800, "id", cfg).collect()}
    assert len(small) == 400 and len(large) == 800 and small < large
    kept = pruning.prune_shifted_gaussian(ranked, 800, "id", cfg, "quota")
    assert kept.count() == 800 and kept.agg(F.min("pct")).first()[0] >= cfg.discard
    n = pruning.prune_shifted_gaussian(ranked, 800, "id", cfg, "poisson").count()
    assert abs(n - 800) < 4 * math.sqrt(800)
    with pytest.raises(ValueError):
        pruning.prune_shifted_gaussian(ranked, 3900, "id", cfg, "quota")
    with pytest.raises(ValueError):
        ShiftedGaussian(spread=0)


def test_unshifted_is_centred(spark, ranked):
    a = pruning.prune_gaussian(ranked, 300, "id", 0.2)
    b = pruning.prune_shifted_gaussian(ranked, 300, "id", ShiftedGaussian(0.0, 0.5, 0.2))
    assert {r.id for r in a.collect()} == {r.id for r in b.collect()}


def test_quota_histogram_follows_the_density(spark, ranked):
    cfg = ShiftedGaussian()
    kept = pruning.prune_shifted_gaussian(ranked, 800, "id", cfg, "quota")
    hist = pruning.selection_histogram(ranked, kept, "id", 10).orderBy("bin").collect()
    want = ranked.withColumn("g", density(F.col("pct"), cfg)).groupBy(F.floor(F.col("pct") * 10).alias("b")).agg(F.sum("g")).orderBy("b").collect()
    total = sum(r[1] for r in want)
    assert all(abs(h.kept - 800 * w[1] / total) <= 11 for h, w in zip(hist, want, strict=True))


def test_water_fill_and_inclusion():
    assert water_fill({0: 1.0, 1: 1.0, 2: 2.0}, {0: 10, 1: 1, 2: 10}, 9) == {0: 3, 1: 1, 2: 5}
    c = inclusion_scale([(100, 0.5), (100, 1.0)], 120)
    assert 100 * min(1, c * 0.5) + 100 * min(1, c) == pytest.approx(120)


def marked(spark, primary, reference):
    soft = softmax_in_batch(scores(spark), "s").withColumn("batch_weight", F.lit(1.0)).withColumn("features", F.array(F.lit(1.0)))
    gap = {i + 1: a - b for i, (a, b) in enumerate(zip(primary, reference, strict=True))}
    m = spark.createDataFrame(list(gap.items()), "id int, mult double")
    return soft.join(m, "id")


def test_rater_gradient_of_the_worked_case(spark):
    g = meta.rater_gradient(marked(spark, (1.0, 2.0, 3.0), (0.0, 0.0, 0.0)), 1).first()
    assert g.mean_mult == pytest.approx(2.0) and g.g_bias == pytest.approx(0.0)
    same = meta.rater_gradient(marked(spark, (1.0, 2.0, 3.0), (1.0, 2.0, 3.0)), 1).first()
    assert same.g0 == 0 and same.mean_mult == 0


def test_proxy_steps_of_the_worked_case(spark):
    rows = spark.createDataFrame([([1.0], 2.0, 0.25), ([2.0], 3.0, 0.75)], "features array<double>, target double, weight double")
    val = spark.createDataFrame([([1.0], 1.0)], "features array<double>, target double")
    assert meta.joint_step(rows, val, (1.0,), 0.1) == pytest.approx([1.175])
    ones = rows.withColumn("weight", F.lit(1.0))
    assert meta.reference_step(ones, (1.0,), 0.1) == pytest.approx([1.3])


def toy(n=40, vocab=8, seed=0):
    rng = np.random.default_rng(seed)
    cells = [np.sort(rng.choice(vocab * vocab, 12, replace=False)) for _ in range(n)]
    counts = [rng.integers(1, 9, 12) for _ in range(n)]
    return Profiles(cells, counts, vocab), rng.normal(size=(n, 6))


def test_bigram_gradient_by_differences():
    p, _ = toy()
    rng = np.random.default_rng(1)
    theta, w = rng.normal(size=(8, 8)), rng.random(len(p))
    g, eps = p.gradient(theta, w), 1e-6
    for a, b in ((0, 0), (3, 5), (7, 2)):
        up, down = theta.copy(), theta.copy()
        up[a, b] += eps
        down[a, b] -= eps
        assert (w @ p.losses(up) - w @ p.losses(down)) / (2 * eps) == pytest.approx(g[a, b], rel=1e-5, abs=1e-9)
    one = p.take(np.array([4]))
    assert p.norms(theta)[4] == pytest.approx(np.linalg.norm(one.gradient(theta, np.ones(1))))


def test_uniform_logits_lose_log_v():
    p, _ = toy()
    assert p.losses(np.zeros((8, 8))) == pytest.approx(np.full(len(p), math.log(8)))
    empty = Profiles([np.zeros(0, dtype=int)], [np.zeros(0)], 8)
    assert empty.losses(np.zeros((8, 8))).tolist() == [0.0]


@pytest.mark.parametrize("group", [True, False])
def test_rater_gradient_by_differences(group):
    _, x = toy()
    rng = np.random.default_rng(2)
    start = Rater.start(RaterConfig(hidden=4, group=group))
    r = start.step({k: rng.normal(size=np.shape(getattr(start, k))) for k in ("w1", "b1", "w2", "g1", "gb1", "g2")}, 0.3)
    mult = rng.normal(size=len(x))

    def value(q):
        a, b = q.weights(x)
        return float(mult @ (a * b))

    g, eps = r.gradient(x, mult), 1e-6
    for name in g:
        if np.ndim(g[name]) == 0:
            continue
        at = tuple(0 for _ in np.shape(g[name]))
        e = np.zeros(np.shape(g[name]))
        e[at] = eps
        numeric = (value(r.step({name: -e}, 1.0)) - value(r.step({name: e}, 1.0))) / (2 * eps)
        assert numeric == pytest.approx(np.asarray(g[name])[at], rel=1e-4, abs=1e-9)


def test_weights_are_bounded_and_constant_multipliers_teach_nothing():
    _, x = toy()
    r = Rater.start(RaterConfig())
    a, b = r.weights(x)
    assert a.sum() == pytest.approx(1) and 0 < b < 1
    g = r.gradient(x, np.full(len(x), 3.0))
    assert np.abs(g["w2"]).max() < 1e-12 and abs(g["b2"]) < 1e-12


def test_first_step_after_hand_over_leaves_the_rater():
    p, x = toy()
    cfg = MetaConfig(vocab=8, steps=1)
    state = warm_up(TrainState.start(cfg), [(p, x)] * 3, cfg)
    assert np.array_equal(state.theta, state.theta_hat)
    after, row = meta_step(state, p, x, p, cfg)
    assert row["mean_mult"] == 0 and np.array_equal(after.rater.w2, state.rater.w2)


def test_loss_rule_drives_the_batch_weight_down():
    p, x = toy()
    cfg = MetaConfig(rule="loss", vocab=8)
    state, log = run_steps(TrainState.start(cfg), p, x, p, cfg, 60, 0)
    assert log[-1]["batch_weight"] < log[0]["batch_weight"]
    assert np.array_equal(state.theta_hat, np.zeros((8, 8)))


def test_gap_rule_with_zero_reference_is_the_loss_rule():
    p, x = toy()
    zero = np.full((8, 8), -60.0)
    np.fill_diagonal(zero, 0)
    diagonal = Profiles([np.array([i * 9]) for i in range(8)] * 5, [np.array([3])] * 40, 8)
    state = TrainState(np.zeros((8, 8)), zero, Rater.start(RaterConfig()))
    a, _ = meta_step(state, diagonal, x, p, MetaConfig(rule="gap", vocab=8))
    b, _ = meta_step(state, diagonal, x, p, MetaConfig(rule="loss", vocab=8))
    assert a.rater.g2 == pytest.approx(b.rater.g2) and a.rater.w2 == pytest.approx(b.rater.w2)


def test_average_and_row_round_trip(spark):
    r = Rater.start(RaterConfig(seed=3))
    assert average([(1, r), (3, r)]).w1 == pytest.approx(r.w1)
    back = Rater.read(r.row(spark, "v1"))
    assert np.array_equal(back.w1, r.w1) and np.array_equal(back.g1, r.g1)


def test_trained_rater_finds_quality(spark):
    from gradsift.catalog.workloads import rater_auc_trained

    assert rater_auc_trained(spark, "/root/testdata/sf0.01").first().auc >= 0.9


def test_shards_agree_statistically(spark):
    from gradsift.functions.features import pool_text
    from gradsift.plans.training import MetaTrainer, rate_corpus
    from gradsift.sources import corpora

    sf = "/root/testdata/sf0.01"
    pool, val = pool_text(corpora.train_pool(spark, sf)), corpora.wanted(spark, sf)
    state, log = MetaTrainer(MetaConfig(), shards=3, rounds=3).run(pool, val)
    labels = corpora.table(spark, sf, "labels")
    assert measures.auc(rate_corpus(pool, state.rater).join(labels, "doc_id"), "score", "quality").first().auc >= 0.9
    assert set(log["shard"]) == {0, 1, 2}


def test_measures_of_worked_cases(spark):
    a = spark.createDataFrame([([-1.0, -1.0],), ([1.0, 1.0],)], "f array<double>")
    b = spark.createDataFrame([([1.0, 3.0],), ([5.0, 5.0],)], "f array<double>")
    assert measures.frechet_diagonal(a, b, "f", 2).first().frechet == pytest.approx(26)
    assert measures.frechet_distance(a, a, "f", 2) == pytest.approx(0, abs=1e-9)
    assert measures.frechet_distance(a, b, "f", 2) == pytest.approx(measures.frechet_distance(b, a, "f", 2))
    p = spark.createDataFrame([([1.0, 0.0], [1.0, 1.0])], "x array<double>, y array<double>")
    assert measures.alignment_score(p, "x", "y").first().alignment == pytest.approx(0.707107, abs=1e-6)
    s = spark.createDataFrame([(3.0, 1), (2.0, 0), (1.0, 1)], "s double, q int")
    assert measures.auc(s, "s", "q").first().auc == pytest.approx(0.5)
    c = spark.createDataFrame([("random", 50.0, 10.0), ("sel", 10.0, 10.0), ("random", 10.0, 30.0)], "method string, elapsed double, value double")
    assert measures.time_to_target(c, "random").first().speedup == pytest.approx(5)


def test_constant_raster_has_no_edges(spark):
    from gradsift.functions import heuristics

    df = spark.createDataFrame([([0.3] * 64,)], "p array<double>")
    r = df.select(heuristics.clarity(F.col("p")).alias("c"), heuristics.frequency(F.col("p")).alias("f"), heuristics.edge_density(F.col("p")).alias("e")).first()
    assert r.c == pytest.approx(0, abs=1e-12) and r.f == 0 and r.e == 0


def test_validation_reports_faults(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0]), (1, [1.0]), (None, [float("nan"), 0.0]), (2, None)], "id long, f array<double>")
    r = validate_corpus(df, SampleSpec("id", features="f"), 2).first()
    assert (r.n, r.null_ids, r.repeated_ids, r.null_features, r.wrong_length, r.not_numbers) == (4, 1, 1, 1, 1, 1)
    with pytest.raises(ValueError):
        bind(df, SampleSpec("id", text="t"))


def test_generate_shape():
    g = generate(np.zeros((8, 8)), 3, 20)
    assert g.shape == (3, 20) and g.max() < 8 and bigram_nll(np.zeros((8, 8)))[0, 0] == pytest.approx(math.log(8))


def test_adapter_and_full_training_lower_the_loss():
    from gradsift.plans.downstream import train_adapter, train_bigram

    p, _ = toy(200)
    start = float(p.losses(np.zeros((8, 8))).mean())
    _, curve = train_bigram(p, 3, 32, 8.0, 0, p)
    adapted = train_adapter(p, p, None, 2, 3, 32, 2.0, 0)
    assert curve[-1][1] < start and adapted[-1][1] < start and [e for e, _ in curve] == [1, 2, 3]


def test_fitted_estimator_separates(spark):
    from gradsift.plans.downstream import fit_estimator

    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, 2))
    y = (x @ np.array([2.0, -1.0]) + 0.5 + rng.logistic(size=400) > 0).astype(int)
    df = spark.createDataFrame([(r.tolist(), int(v)) for r, v in zip(x, y, strict=True)], "f array<double>, y int")
    w, b = fit_estimator(df, "f", "y")
    assert w[0] == pytest.approx(2, abs=0.6) and w[1] == pytest.approx(-1, abs=0.5) and b == pytest.approx(0.5, abs=0.5)


def test_bilevel_grid_agrees_with_iterated_steps(spark):
    """The closed form of a candidate against descent on its weighted loss."""
    rng = np.random.default_rng(1)
    x = rng.random(60)
    y = 0.7 * x + 0.1 * rng.normal(size=60)
    train = spark.createDataFrame([(float(a), float(b)) for a, b in zip(x, y, strict=True)], "x double, y double")
    grid = spark.createDataFrame([(0, 0.0), (1, 1.5)], "candidate int, c double")
    got = {r.candidate: r for r in meta.solve_bilevel_grid(train, train, grid).collect()}
    for k, c in ((0, 0.0), (1, 1.5)):
        w, theta = np.exp(c * x), 0.0
        for _ in range(2000):
            theta -= 0.02 * float(w @ ((theta * x - y) * x)) / len(x)
        assert got[k].theta == pytest.approx(theta, abs=1e-4)
    assert sum(r.best for r in got.values()) == 1


def test_logistic_and_scale_gradients_by_differences(spark):
    from gradsift.operators import proxies

    df = spark.createDataFrame([([0.3, -0.7], 1.0), ([1.2, 0.4], 0.0)], "f array<double>, y double")
    theta, eps = (0.2, -0.5), 1e-5
    f, y = F.col("f"), F.col("y")
    g = df.select(proxies.logistic_gradient(f, y, theta).alias("g")).collect()
    up = df.select(proxies.logistic_loss(f, y, (0.2 + eps, -0.5)).alias("l")).collect()
    down = df.select(proxies.logistic_loss(f, y, (0.2 - eps, -0.5)).alias("l")).collect()
    assert [(a.l - b.l) / (2 * eps) for a, b in zip(up, down, strict=True)] == pytest.approx([r.g[0] for r in g], rel=1e-5)


def prose(spark, n: int, seed: int = 0):
    rng = np.random.default_rng(seed)
    words = np.array("alpha beta gamma delta one two three four red green".split())
    return spark.createDataFrame([(i, " ".join(words[rng.integers(0, 10, 6)])) for i in range(n)], "doc_id long, text string")


def test_downstream_models_train_on_every_row_of_a_selection(spark):
    from gradsift.plans import downstream, experiments

    docs = prose(spark, 4600)
    sets = {"full": docs, "half": docs.where("doc_id % 2 = 0")}
    got = {(r.method, r.epoch): r for r in experiments.trained_on(sets, docs, docs.limit(50), epochs=2).collect()}
    assert (got["full", 1].k, got["half", 1].k) == (4600, 2300) and got["full", 2].visits == 9200
    stack = experiments.stacked(sets, ["doc_id"])
    cut = {(r.method, r.epoch): r for r in downstream.train_methods(stack, docs, docs.limit(50), epochs=2, shard_rows=1600).collect()}
    assert (cut["full", 1].k, cut["half", 1].k) == (4600, 2300)
    assert cut["full", 2].val_loss < cut["full", 1].val_loss and cut["full", 2].val_loss < cut["half", 2].val_loss < math.log(32)


def test_mean_profile_gives_the_mean_loss(spark):
    from gradsift.plans import downstream

    docs = prose(spark, 40)
    held = downstream.with_profiles(docs, "doc_id", "text", 32, []).toPandas()
    logits = np.random.default_rng(1).normal(size=(32, 32))
    mean = downstream.Profiles(list(held["cells"]), list(held["counts"]), 32).losses(logits).mean()
    assert downstream.mean_profile(docs, "text", 32) @ bigram_nll(logits).ravel() == pytest.approx(mean)


def test_trained_scores_hold_the_group_part(spark):
    from dataclasses import replace

    from gradsift.functions.features import pool_text
    from gradsift.operators.batching import assign_batches
    from gradsift.plans.experiments import rated_ranks

    rng = np.random.default_rng(5)
    rater = replace(Rater.start(RaterConfig(seed=2)), w2=rng.normal(size=16), g2=rng.normal(size=16), gb2=0.3)
    docs = prose(spark, 150)
    got = {r.doc_id: r.score for r in rated_ranks(docs, TrainState(None, None, rater)).collect()}
    own = assign_batches(pool_text(docs), "doc_id").select("doc_id", "batch_id", "features").toPandas()
    for _, f in own.groupby("batch_id"):
        x = np.array(f["features"].tolist())
        want = rater.raw(x) + np.log(rater.batch_weight(x))
        assert [got[i] for i in f["doc_id"]] == pytest.approx(want.tolist())
    alone = {r.doc_id: r.score for r in rated_ranks(docs, TrainState(None, None, replace(rater, group=False))).collect()}
    assert len(got) == len(alone) == 150 and max(abs(got[i] - alone[i]) for i in got) > 0.01


def test_batches_go_on_and_leave_no_row_out():
    from gradsift.plans.training import _batches

    p, x = Profiles([np.array([i]) for i in range(10)], [np.array([1])] * 10, 4), np.arange(10.0)[:, None]
    all_at_once = [b[:, 0].tolist() for _, b in _batches(p, x, 4, 6, 0)]
    assert all_at_once == [b[:, 0].tolist() for s in (0, 2, 4) for _, b in _batches(p, x, 4, 2, 0, s)]
    assert {v for b in all_at_once[:3] for v in b} == set(range(10))


def test_rater_trains_on_every_row(spark, monkeypatch):
    from gradsift.functions.features import pool_text
    from gradsift.plans import training

    docs = pool_text(prose(spark, 20_500))
    cfg = MetaConfig(rater=RaterConfig(hidden=2))
    seen = []
    average_of = training.average
    monkeypatch.setattr(training, "average", lambda states: seen.append([n for n, _ in states]) or average_of(states))
    _, log = training.MetaTrainer(cfg, shards=0, rounds=2).run(docs.select("doc_id", "text", "features"), prose(spark, 2300, 1))
    assert [sum(s) for s in seen] == [20_500, 20_500] and len(seen[0]) == training.shards_for(cfg, 20_500) == 3
    assert max(seen[0]) <= cfg.steps * cfg.batch and len(log) == 900


def test_dynamics_trace_every_pool_document(spark, monkeypatch):
    from gradsift.catalog.measures import exp_dynamics_trained
    from gradsift.plans import downstream
    from gradsift.sources import corpora

    sf = "/root/testdata/sf0.01"
    trained, traced, by_range, epochs_of = [], [], measures.dynamics_by_range, downstream.train_epochs

    def epochs(selections, *args):
        for epoch, models in epochs_of(selections, *args):
            trained.append(models["pool"][0])
            yield epoch, models

    monkeypatch.setattr(downstream, "train_epochs", epochs)
    monkeypatch.setattr(measures, "dynamics_by_range", lambda t, *rest: traced.append(t.count()) or by_range(t, *rest))
    rows = exp_dynamics_trained(spark, sf).collect()
    n = corpora.train_pool(spark, sf).count()
    assert n > 500 and trained == [n] * 5 and traced == [6 * n]
    assert len(rows) == 10 and all(r.loss_slope < 0 for r in rows)


def test_comparison_takes_rare_words_and_the_best_pruning(spark, monkeypatch):
    from gradsift.functions.features import pool_text
    from gradsift.plans import experiments

    docs = spark.createDataFrame([(1, "a a b"), (2, "a b c"), (3, "a b"), (4, "a b"), (5, "a d d d")], "doc_id long, text string")
    ranks = experiments.heuristic_ranks(pool_text(docs))
    assert set(ranks) == {"aesthetic", "clarity", "frequency", "edges"}
    assert {r.doc_id: round(r.score, 6) for r in ranks["frequency"].collect()} == {1: 0.0, 2: 0.333333, 3: 0.0, 4: 0.0, 5: 0.75}

    trained = []

    def fake(sets, *_, **__):
        trained.extend(sets)
        rows = [(m, 1, 1, 1, 1.0 if m.endswith("_middle") else 2.0) for m in sets]
        return spark.createDataFrame(rows, "method string, k long, epoch int, visits long, val_loss double")

    monkeypatch.setattr(experiments, "trained_on", fake)
    got = {r.method for r in experiments.comparison(spark, "/root/testdata/sf0.001").collect()}
    assert {"frequency_top", "frequency_middle"} <= set(trained)
    assert got == {"full", "random", "shifted_20", "shifted_50"} | {f"{m}_middle" for m in ranks}


# ranking: the number of bins, and awkward inputs


def test_bins_follow_the_rows():
    from gradsift.operators import ranking

    assert [ranking.bins_for(n) for n in (0, 10, 100_000, 100_001, 10**8)] == [1, 1, 1, 2, 1000]
    assert ranking.bins_for(10**12) == ranking.MAX_BINS


@pytest.mark.parametrize("bins", [1, 16])
@pytest.mark.parametrize("text_ids", [False, True])
def test_ranks_without_scores_with_ties_and_clashing_names(spark, bins, text_ids):
    """Null and NaN scores come last, by id; a score that most rows share is split by id of any type."""
    scores = [1.0] * 300 + [None, float("nan"), None] + [float(i % 7) for i in range(100)]
    rows = [((f"id{i:04d}" if text_ids else i), s, i, -i, 7) for i, s in enumerate(scores)]
    df = spark.createDataFrame(rows, f"id {'string' if text_ids else 'long'}, s double, _bin long, _in long, `_key` int").repartition(5)
    for descending in (True, False):
        def order(r):
            bad = r[1] is None or r[1] != r[1]
            return bad, 0.0 if bad else (-r[1] if descending else r[1]), r[0]

        want = {r[0]: k for k, r in enumerate(sorted(rows, key=order), 1)}
        got = rank_corpus(df, "s", "id", bins=bins, descending=descending)
        assert got.columns == [*df.columns, "rank", "pct"]
        found = got.collect()
        assert {r.id: r["rank"] for r in found} == want and all(r["_bin"] == -r["_in"] for r in found)
    wanted = {i for i, k in want.items() if k <= 250}
    assert {r.id for r in select_smallest(df, "s", 250, "id", bins=bins).collect()} == wanted
    assert rank_corpus(df.limit(0), "s", "id", bins=bins).count() == 0


def test_a_shared_score_is_split_over_tasks(spark):
    from gradsift.operators import ranking

    df = spark.range(20_000).select(F.concat(F.lit("k"), "id").alias("id"), F.lit(0.5).alias("_s")).withColumn("b", F.lit(0.0))
    parts = ranking._with_part(df, "b", "sub", "id", {0.0: 20_000}, {0.0: 40}).groupBy("sub").count().collect()
    assert len(parts) > 30 and max(r["count"] for r in parts) < 3000


def test_quota_sampler_in_parts_equals_one_part(spark, monkeypatch):
    from gradsift.operators import pruning

    ranked = rank_corpus(spark.range(4000).select("id", F.sin(F.col("id").cast("double")).alias("s")), "s", "id").cache()
    whole = {r.id for r in pruning.prune_shifted_gaussian(ranked, 800, "id", sampler="quota").collect()}
    monkeypatch.setattr(pruning, "bins_for", lambda n: 9)
    assert {r.id for r in pruning.prune_shifted_gaussian(ranked, 800, "id", sampler="quota").collect()} == whole and len(whole) == 800


def test_exact_copies_leave_the_first(spark):
    from gradsift.operators.batching import dedup_exact

    df = spark.createDataFrame([(3, "a"), (1, "a"), (2, "b"), (4, None), (5, None), (6, "")], "doc_id long, text string")
    assert sorted(r.doc_id for r in dedup_exact(df).collect()) == [1, 2, 4, 6]
    assert dedup_exact(df.limit(0)).count() == 0


def test_softmax_family_learns_the_language(spark):
    from gradsift.plans.downstream import class_shares, train_softmax

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    rows = class_shares(docs, "doc_id", "text", "lang")
    sets = docs.select(F.lit("all").alias("method"), "doc_id")
    curve = {r.epoch: (r.val_loss, r.k) for r in train_softmax(sets, rows, rows, ["de", "en", "es", "fr"], steps=8).collect()}
    assert curve[0][0] == pytest.approx(math.log(4)) and curve[8][0] < 0.9 * curve[0][0] and curve[0][1] == docs.count()
