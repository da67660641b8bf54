"""The validation of the methods: gradients, worked example, route parity, exact answers, samples and orders."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from gradfold.functions import hashing as H
from gradfold.functions import vectors as V
from gradfold.operators import baselines, chain, factor, folds, loop, metrics, models, mrs, parallel, prox, sampling, series, steps, stop
from gradfold.operators.ordering import Alternating, Clustered, LocalShuffle, Reverse, ShuffleAlways, ShuffleOnce, Stored
from gradfold.operators.ranks import ranked
from gradfold.operators.tasks import LINEAR, LR, LSQ, SVM
from gradfold.plans import fixtures as X


@pytest.mark.parametrize("name", ["lr", "svm", "lsq", "huber", "poisson"])
def test_move_is_minus_the_gradient(name):
    task, rng = LINEAR[name], np.random.default_rng(1)
    for _ in range(50):
        w, x, y = rng.normal(size=3), rng.normal(size=3), float(rng.choice([-1.0, 1.0]))
        if abs(1 - y * (w @ x)) < 1e-3 or abs(abs(w @ x - y) - 1) < 1e-3:
            continue
        g = np.array([(task.loss_np((w + h) @ x, y) - task.loss_np((w - h) @ x, y)) / 2e-6 for h in np.eye(3) * 1e-6])
        assert np.allclose(-task.move_np(w @ x, y) * x, g, atol=1e-5)


@pytest.mark.parametrize("name", sorted(LINEAR))
def test_columns_and_arrays_agree(spark, name):
    task = LINEAR[name]
    data = [(u / 4, y) for u in range(-12, 13) for y in (-1.0, 1.0)]
    got = spark.createDataFrame(data, "u double, y double").select("u", "y", task.move(F.col("u"), F.col("y")).alias("m"), task.loss(F.col("u"), F.col("y")).alias("l")).collect()
    for r in got:
        assert np.isclose(r.m, task.move_np(r.u, r.y)) and np.isclose(r.l, task.loss_np(r.u, r.y))


def test_simplex_projection(spark):
    rng = np.random.default_rng(2)
    for _ in range(20):
        v = rng.normal(size=5)
        w = prox.onto_simplex(v)
        assert abs(w.sum() - 1) < 1e-12 and (w >= 0).all()
        other = prox.onto_simplex(rng.normal(size=5))
        assert np.linalg.norm(v - w) <= np.linalg.norm(v - other) + 1e-12
        col = spark.range(1).select(prox.simplex().column(V.literal(v.tolist()), 1.0).alias("w")).first().w
        assert np.allclose(col, w)


def test_lazy_penalties():
    rng = np.random.default_rng(3)
    w, eager, lazy = np.zeros(6), np.zeros(6), prox.LazyL1(6, 0.3)
    for _ in range(40):
        idx = rng.choice(6, 2, replace=False)
        d = rng.normal(size=2)
        lazy.touch(w, idx)
        w[idx] += d
        lazy.spend(0.05)
        eager[idx] += d
        eager = prox.soft(eager, 0.05 * 0.3)
    assert np.allclose(lazy.settle(w), eager)


def test_closed_form_of_constant_steps():
    n, a, w = 500, 0.01, 1.0
    for _ in range(200):
        for y in [1.0] * n + [-1.0] * n:
            w -= a * (w - y)
    q = (1 - a) ** n
    assert abs(w + (1 - q) / (1 + q)) < 1e-9


@pytest.mark.parametrize("tags", [1, 2, 3, 5])
@pytest.mark.parametrize("size", [1, 40, 900])
def test_chain_marginals_in_scaled_numbers(tags, size):
    import time

    from gradfold.operators import chain

    rng = np.random.default_rng(tags)
    for length in (1, 2, 64):
        c, pot = chain.Chain(rng.normal(size=(9, tags)), size * rng.normal(size=(tags, tags))), size * rng.normal(size=(length, tags))
        start = time.perf_counter()
        single, pair, z = c.marginals(pot)
        mine = time.perf_counter() - start
        start = time.perf_counter()
        f, b = c.forward(pot), c.backward(pot)
        theirs = time.perf_counter() - start
        assert np.allclose(single, np.exp(f + b - z), atol=1e-9) and np.isclose(z, chain._lse(f[-1], 0))
        assert np.allclose(pair.sum(), length - 1)
    if size == 1:
        assert mine < theirs / 2  # it took longer than both recursions before


def test_chain_step_of_flat_features():
    from gradfold.operators import chain

    rng = np.random.default_rng(3)
    one, other = chain.Chain.zero(20, 3), chain.Chain.zero(20, 3)
    for _ in range(30):
        feats = [rng.integers(0, 20, rng.integers(0, 5)).tolist() for _ in range(rng.integers(1, 9))]
        tags = rng.integers(0, 3, len(feats))
        emit, move, loss = one.gradient(feats, tags)[1:]
        for f, e in zip(feats, emit, strict=True):
            np.add.at(one.emit, np.array(f, int), 0.3 * e)
        one.move += 0.3 * move
        at = np.repeat(np.arange(len(feats)), [len(f) for f in feats])
        assert np.isclose(loss, other.step_flat(np.array(sum(feats, []), int), at, tags, 0.3))
    assert np.allclose(one.emit, other.emit) and np.allclose(one.move, other.move)


def test_random_order_needs_fewer_epochs(spark, sf):
    from gradfold.plans import orders

    got = {r.run: r.epochs for r in orders.catx_epochs(spark, sf).collect()}
    assert got["random"] < got["clustered"]
    assert all(r.epochs < got["clustered"] for r in orders.catx_permutations(spark, sf).collect())


def tiny(spark, sf):
    return X.tiny(spark, sf).withColumn("k", H.order_key(42, F.col("id")))


def arrays(df):
    got = df.orderBy("k").collect()
    return np.array([r.x for r in got]), np.array([r.y for r in got])


@pytest.mark.parametrize("task", [LR, SVM, LSQ])
def test_routes_agree(spark, sf, task):
    df = tiny(spark, sf)
    x, y = arrays(df)
    want = baselines.numpy_igd(x, y, task, 0.1)
    one = df.withColumn("seg", F.lit(0).cast("long")).repartition(1, "seg")
    routes = [folds.fold_catalyst(df, task, [0.0] * X.D, 0.1).first().w]
    routes += [folds.fold_arrow(one, task, np.zeros(X.D), 0.1, state=s).first().w for s in ("inplace", "passed")]
    routes.append(parallel.simulate(task, x, y, 0.1, "lock"))
    routes.append(parallel.simulate(task, x, y, 0.1, "nolock", workers=1))
    routes.append(loop.fit(X.tiny(spark, sf), task, X.D, ShuffleOnce(), steps.Constant(0.1), stop=stop.MaxEpochs(1)).w)
    for w in routes:
        assert np.allclose(w, want, atol=1e-12)


def test_multiplexed_without_memory_is_clustered(spark, sf):
    df = X.tiny(spark, sf)
    order = [F.desc("y"), F.asc("id")]
    steps_ = mrs.schedule(df, order, 0, 1, mem_steps=0, io_target="arriving").select(F.struct("epoch", "p", "sub").alias("k"), "x", "y")
    a = folds.fold_catalyst(steps_, LR, [0.0] * X.D, 0.1).first().w
    b = folds.fold_catalyst(Clustered().apply(df), LR, [0.0] * X.D, 0.1).first().w
    assert np.allclose(a, b, atol=1e-12)


def test_reservoir_is_the_sequential_one(spark, sf):
    df = X.emb_half(spark, sf).select("id", "y").where("id < 200")
    placed = sampling.slots(sampling.positions(df, [F.asc("id")]), 10, 42).orderBy("p").collect()
    held, gone = {}, []
    for r in placed:
        if r.slot < 10:
            if r.slot in held:
                gone.append((r.p, held[r.slot]))
            held[r.slot] = r.id
        else:
            gone.append((r.p, r.id))
    slotted = sampling.slots(sampling.positions(df, [F.asc("id")]), 10, 42)
    assert {r.slot: r.id for r in sampling.reservoir(slotted, 10).collect()} == held
    assert sorted((r.at, r.id) for r in sampling.drops(slotted, 10).collect()) == sorted(gone)


def test_orders_are_permutations(spark, sf):
    df = X.emb_half(spark, sf).select("id", "y")
    base = sorted(r.id for r in df.collect())
    seen = []
    for order, e in ((Stored(), 1), (Clustered(), 1), (ShuffleOnce(), 1), (ShuffleAlways(), 1), (ShuffleAlways(), 2)):
        ids = [r.id for r in order.apply(df, e).orderBy("k").collect()]
        assert sorted(ids) == base
        seen.append(tuple(ids))
    assert len(set(seen)) == 5


def test_clustered_order_learns_slower(spark, sf):
    df = X.emb_half(spark, sf)
    once = loop.fit(df, LR, X.D, ShuffleOnce(), steps.PerEpoch(1.0, 0.5), stop=stop.MaxEpochs(10)).history[-1]["loss"]
    clustered = loop.fit(df, LR, X.D, Clustered(), steps.PerEpoch(1.0, 0.5), stop=stop.MaxEpochs(10)).history[-1]["loss"]
    assert once < 0.8 * clustered


def test_averaging_with_one_part_is_serial_and_more_parts_still_learn(spark, sf):
    df = X.emb_half(spark, sf)
    serial = loop.fit(df, LR, X.D, step=steps.PerEpoch(0.05), stop=stop.MaxEpochs(3))
    parts = loop.fit(df, LR, X.D, step=steps.PerEpoch(0.05), stop=stop.MaxEpochs(3), parts=4)
    assert serial.history[-1]["loss"] <= parts.history[-1]["loss"] < loop.objective(df, LR, np.zeros(X.D))


def test_stop_rules(spark, sf):
    df = X.part_price(spark, sf)
    assert loop.objective(df, LSQ, baselines.exact_lsq(df, 3)) < 1e-9
    fit = loop.fit(df, LSQ, 3, step=steps.PerEpoch(0.05, 1), stop=stop.TargetLoss(1e-3) | stop.MaxEpochs(12))
    assert len(fit.history) < 12
    e = X.emb_half(spark, sf)
    best = loop.objective(e, LR, baselines.newton_lr(e, X.D, 4))
    for rule in (stop.OptGap(best, 0.5), stop.Multiple(best, 2.0)):
        assert len(loop.fit(e, LR, X.D, step=steps.PerEpoch(0.1), stop=rule | stop.MaxEpochs(9)).history) < 9
    norm = loop.fit(df, LSQ, 3, step=steps.PerEpoch(0.05, 1), stop=stop.GradNorm(1e9) | stop.MaxEpochs(3))
    assert len(norm.history) == 1
    sql = loop.fit(df, LSQ, 3, step=steps.Constant(0.01), stop=stop.SqlPredicate(spark, "select max(epoch) >= 2 from history"))
    assert len(sql.history) == 2
    drop = loop.fit(df, LSQ, 3, step=steps.PerEpoch(0.05, 1), stop=stop.RelDrop(0.5) | stop.MaxEpochs(9))
    assert len(drop.history) < 9  # the loss falls to nothing: the floor ends it
    drop = loop.fit(e, LR, X.D, step=steps.PerEpoch(0.1), stop=stop.RelDrop(0.2, 0.0) | stop.MaxEpochs(9))
    losses = [h["loss"] for h in drop.history]
    assert 1 < len(losses) < 9 and losses[-2] - losses[-1] <= 0.2 * losses[-2]
    chain3 = stop.GradNorm(1e-30) | stop.RelDrop(1e-30, 0.0) | stop.MaxEpochs(2)
    assert chain3.wants_gradient and not (stop.RelDrop(0.1) | stop.MaxEpochs(2)).wants_gradient
    assert len(loop.fit(df, LSQ, 3, step=steps.PerEpoch(0.05, 1), stop=chain3).history) == 2
    assert len(loop.fit(df, LSQ, 3, stop=stop.MaxSeconds(0.0)).history) == 1
    assert len(loop.fit(df, LSQ, 3, stop=stop.ModelPredicate(lambda w: True)).history) == 1


def test_segments_fill_their_partitions(spark, sf):
    keyed = X.line_dense(spark, sf).withColumn("k", H.fast(42, F.col("id")))
    for parts in (1, 4, 8, 64):
        got = loop.segments(keyed, parts).groupBy(F.spark_partition_id().alias("p")).agg(F.countDistinct("seg").alias("n")).collect()
        assert len(got) == parts and all(r.n == 1 for r in got)


def test_local_shuffle_trains_in_place(spark, sf):
    df = X.emb_half(spark, sf).repartition(4).persist()
    plain = loop.fit(df, LR, X.D, ShuffleOnce(), steps.Constant(0.05), parts=4, stop=stop.MaxEpochs(3))
    local = loop.fit(df, LR, X.D, LocalShuffle(buffer=7), steps.Constant(0.05), stop=stop.MaxEpochs(3))
    assert local.history[-1]["steps"] == plain.history[-1]["steps"] == 3 * df.count()
    assert abs(local.history[-1]["loss"] / plain.history[-1]["loss"] - 1) < 0.2
    assert local.history[0]["loss"] > local.history[-1]["loss"]
    df.unpersist()


def test_reverse_and_alternating(spark, sf):
    df = X.emb_half(spark, sf).select("id", "y")
    ids = [r.id for r in df.orderBy("id").collect()]
    at = lambda order, e: [r.id for r in order.apply(df, e).orderBy("k").collect()]
    assert at(Reverse(), 1) == ids[::-1] and at(Alternating(), 1) == ids and at(Alternating(), 2) == ids[::-1]


def test_fit_takes_samples(spark, sf):
    df = X.emb_half(spark, sf)
    fit = loop.fit(df, LR, X.D, step=steps.Constant(0.1), stop=stop.MaxEpochs(1), sample=lambda d, e: sampling.bottom_m(d, 20, seed=e))
    assert fit.history[0]["steps"] == 20


def test_ranks_are_places(spark, sf):
    df = X.line_dense(spark, sf).select("id", "y").distinct()
    got, n = ranked(df, [F.desc("y"), F.asc("id")], "rank")
    rows = got.orderBy("rank").collect()
    assert n == len(rows) and [r.rank for r in rows] == list(range(n))
    assert [(r.y, r.id) for r in rows] == sorted(((r.y, r.id) for r in rows), key=lambda v: (-v[0], v[1]))
    assert ranked(df.where("false"), [F.asc("id")], "rank")[1] == 0



def test_null_rows_are_dropped_and_counted(spark):
    df = spark.createDataFrame([(1, [1.0], 1.0), (2, None, 1.0), (3, [1.0], None)], "id long, x array<double>, y double")
    fit = loop.fit(df, LSQ, 1, stop=stop.MaxEpochs(1))
    assert fit.dropped == 2 and fit.history[0]["steps"] == 1


def test_partitioned_reservoirs_beat_clustered(spark, sf):
    df = X.emb_half(spark, sf).repartitionByRange(2, F.desc("y"), "id").sortWithinPartitions(F.desc("y"), "id")
    alpha = steps.PerEpoch(0.5)
    w, history = mrs.fit_partitioned(df, LR, X.D, 50, 3, alpha, mem_steps=2)
    clustered = loop.fit(X.emb_half(spark, sf), LR, X.D, Clustered(), alpha, stop=stop.MaxEpochs(3)).w
    assert history[0]["rows"] == df.count()
    assert loop.objective(df, LR, w) < loop.objective(df, LR, clustered)


def test_shared_memory_schemes(spark, sf):
    df = tiny(spark, sf).repartition(2, "k").persist()
    start = loop.objective(df, LR, np.zeros(X.D))
    for scheme in parallel.SCHEMES:
        model = parallel.SharedModel(X.D)
        try:
            assert parallel.shared_epoch(df, LR, model, 0.1, scheme) == 50
            assert loop.objective(df, LR, model.w.copy()) < start
        finally:
            model.close()


def test_models_save_load_and_predict(spark, sf, tmp_path):
    path = str(tmp_path / "models")
    models.save(spark, path, "r", 1, "lr", [0.0] * X.D)
    models.save(spark, path, "r", 2, "lr", [1.0] * X.D)
    w, task = models.load(spark, path, "r")
    assert task == "lr" and w[0] == 1.0 and models.load(spark, path, "r", 1)[0][0] == 0.0
    cells = spark.createDataFrame([(1, 0, 2.0), (1, 1, 3.0)], "id long, feature long, value double")
    weights = spark.createDataFrame([(0, 1.0), (1, 2.0)], "feature long, w double")
    assert models.predict_sparse(cells, weights).first().margin == 8.0


# factorisation


def test_strata_fit_planted_rank(spark, sf):
    cells = X.rank4(spark, sf).where("i < 60 and j < 120")
    store = lambda df: spark.createDataFrame(df.toPandas(), df.schema)
    _, losses = factor.fit_strata(cells, 4, 4, steps.PerEpoch(0.05, 0.25), parts=2, size=1.0, store=store)
    assert losses[-1] < losses[0]


def test_rank_one_step_moves_both_sides():
    l, r = np.array([[1.0]]), np.array([[2.0]])
    assert factor.walk_cells(l, r, np.array([0]), np.array([0]), np.array([5.0]), 0.1) == 9.0
    assert np.isclose(l[0, 0], 1 + 0.6 * 2) and np.isclose(r[0, 0], 2 + 0.6 * 1)


# sequences


def brute(model, feats):
    pot = model.potentials(feats)
    return {p: model.score(pot, p) for p in itertools.product(range(3), repeat=len(feats))}


def test_chain_against_all_paths():
    rng = np.random.default_rng(5)
    model = chain.Chain(rng.normal(size=(6, 3)), rng.normal(size=(3, 3)))
    for n in (1, 2, 3, 4):
        feats = [list(rng.choice(6, 2)) for _ in range(n)]
        tags = list(rng.choice(3, n))
        scores = brute(model, feats)
        z = np.log(sum(np.exp(s) for s in scores.values()))
        assert np.isclose(model.loss(feats, tags), z - scores[tuple(tags)])
        assert tuple(model.decode(feats)) == max(scores, key=scores.get)
        single, pair, _ = model.marginals(model.potentials(feats))
        assert np.allclose(single.sum(axis=1), 1) and np.isclose(pair.sum(), n - 1)


def test_chain_gradient():
    rng = np.random.default_rng(6)
    model = chain.Chain(rng.normal(size=(4, 3)), rng.normal(size=(3, 3)))
    feats, tags = [[0, 1], [2], [3, 0]], [0, 2, 1]
    before = model.loss(feats, tags)
    _, emit, move, _ = model.gradient(feats, tags)
    h = 1e-6
    model.move[0, 2] += h
    assert np.isclose((model.loss(feats, tags) - before) / h, -move[0, 2], atol=1e-4)
    model.move[0, 2] -= h
    model.emit[2, 1] += h
    assert np.isclose((model.loss(feats, tags) - before) / h, -emit[1, 1], atol=1e-4)


# series


def test_smoothing_walk_reaches_the_exact_answer():
    rng = np.random.default_rng(7)
    y = np.cumsum(rng.normal(size=(12, 1)), axis=0)
    exact = series.smooth_exact(y, w0=np.zeros(1))
    w, t = np.zeros((12, 1)), np.arange(1, 13)
    for e in range(1, 4000):
        p = rng.permutation(12)
        series.smooth_walk(w, t[p], y[p], 0.2 / e**0.6, np.eye(1), np.eye(1), np.zeros(1))
    assert np.allclose(w, exact, atol=0.05)


def test_portfolio_near_the_exact_one():
    rng = np.random.default_rng(8)
    r = rng.normal([0.01, 0.02, 0.0], [0.05, 0.2, 0.1], size=(40, 3))
    w, best = np.full(3, 1 / 3), series.portfolio_exact(r)
    for e in range(1, 400):
        w = series.portfolio_walk(w, r, 20 / e**0.5, r.mean(axis=0))
    assert abs(w.sum() - 1) < 1e-9 and (w >= 0).all()
    assert series.portfolio_objective(w, r) <= series.portfolio_objective(best, r) + 2e-4


# measures


def test_auc_counts_pairs(spark):
    df = spark.createDataFrame([(1.0, 0.9), (1.0, 0.4), (-1.0, 0.4), (-1.0, 0.1)], "y double, score double")
    assert metrics.auc(df).first().auc == 0.875


def test_native_and_ours_reach_like_objectives(spark, sf):
    df = X.emb_half(spark, sf).persist()
    best = loop.objective(df, LR, baselines.newton_lr(df, X.D))
    assert loop.objective(df, LR, baselines.mllib_lr(df)) <= best * 1.01
    ours = loop.fit(df, LR, X.D, step=steps.PerEpoch(1.0, 0.7), stop=stop.MaxEpochs(12))
    assert ours.history[-1]["loss"] <= best * 1.05


def test_new_tasks_are_few_lines():
    import inspect

    from gradfold.operators import tasks

    text = inspect.getsource(tasks)
    for name in ("LR", "SVM", "LSQ", "HUBER"):
        body = text.split(f"\n{name} = LinearTask(")[1].split("\n)\n")[0]
        assert body.count("\n") <= 24


def test_results_do_not_depend_on_partitions(spark, sf):
    df = X.emb_half(spark, sf)
    keep = spark.conf.get("spark.sql.shuffle.partitions")
    got = []
    for n in ("1", "4", "16"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        got.append(loop.fit(df, LR, X.D, stop=stop.MaxEpochs(1), parts=3).w.round(9).tolist())
    spark.conf.set("spark.sql.shuffle.partitions", keep)
    assert got[0] == got[1] == got[2]


def test_softmax_over_segments(spark, sf):
    from gradfold.operators import softmax
    from gradfold.plans import training

    rows = training.classed(spark, sf)
    df = rows.withColumn("k", H.order_key(42, F.col("id")))
    got = df.orderBy("k").collect()
    x, c = np.array([r.x for r in got]), np.array([r.c for r in got])
    w = softmax.fold(df.withColumn("seg", F.lit(3).cast("long")).repartition(1), 10, X.D, 0.1).first()
    want = np.zeros((10, X.D))
    for a, k in zip(x, c):
        p = softmax.chances(want, a[None, :])[0]
        p[k] -= 1
        want -= 0.1 * p[:, None] * a
    w = np.array(w.w).reshape(10, -1)
    assert np.allclose(w, want)
    p = softmax.chances(w, x)
    value = softmax.loss(rows, w).first()
    assert value.n == len(c) and np.isclose(value.loss, -np.log(p[np.arange(len(c)), c]).sum())
    told = {r.id: r.prediction for r in softmax.predict(rows, w).select("id", "prediction").collect()}
    assert [told[r.id] for r in got] == p.argmax(axis=1).tolist()


def test_smoothing_sweep_is_the_dense_solution():
    rng = np.random.default_rng(5)
    y = rng.normal(size=(40, 1))
    n = len(y)
    big, rhs = np.zeros((n, n)), y[:, 0].copy()
    for t in range(n):
        big[t, t] += 2
        if t:
            big[t - 1, t - 1] += 1
            big[t, t - 1] = big[t - 1, t] = -1
    assert np.allclose(series.smooth_exact(y, w0=np.zeros(1))[:, 0], np.linalg.solve(big, rhs))
    assert series.smooth_exact(np.zeros((0, 1))).shape == (0, 1)


def test_portfolio_fold_is_the_walk(spark):
    rng = np.random.default_rng(6)
    r = rng.normal(0.01, 0.05, size=(60, 4))
    df = spark.createDataFrame([(i, row.tolist()) for i, row in enumerate(r)], "k int, r array<double>")
    w = np.full(4, 0.25)
    for e in (1, 2, 3):
        w = series.portfolio_walk(w, r, 5 / e, r.mean(axis=0))
    assert np.allclose(series.fit_portfolio(df, 4, 3, lambda e: 5 / e), w)


def test_strata_are_the_serial_walk_of_their_diagonals(spark):
    """Any number of blocks, against plain loops over the diagonals in the same order; rows and columns of every integer type."""
    rng = np.random.default_rng(8)
    data = sorted({(int(a), int(b)) for a, b in zip(rng.integers(0, 30, 200), rng.integers(0, 25, 200))})
    cells = [(a, b, float(rng.normal())) for a, b in data]
    df = spark.createDataFrame(cells, "i int, j long, m double")
    parts, rank = 3, 2
    side = lambda s, c: {r[0]: r[1] for r in df.select(F.col(c).cast("long").alias("v"), F.pmod(F.xxhash64(F.lit(s), F.col(c).cast("long")), F.lit(parts)).alias("b")).distinct().collect()}
    bi, bj = side("L", "i"), side("R", "j")
    start = {(r.side, r.id): np.array(r.f) for r in factor.initial(df.withColumn("i", F.col("i").cast("long")), rank).collect()}
    losses = []
    for e in (1, 2):
        total = 0.0
        for s in range(parts):
            for a, b, m in cells:  # ordered by row and column
                if (bj[b] - bi[a]) % parts == s:
                    x, y = start["L", a], start["R", b]
                    err = m - x @ y
                    total += err * err
                    start["L", a], start["R", b] = x + 0.1 / e * 2 * err * y, y + 0.1 / e * 2 * err * x
        losses.append(total)
    got, met = factor.fit_strata(df, rank, 2, lambda e: 0.1 / e, parts=parts, key=F.struct(F.col("i"), F.col("j")))
    assert np.allclose(met, losses)
    found = {(r.side, r.id): np.array(r.f) for r in got.collect()}
    assert set(found) == set(start) and all(np.allclose(found[k], start[k]) for k in start)


@pytest.mark.parametrize("threaded", [False, True])
@pytest.mark.parametrize("swap", ["pass", "period"])
def test_partitioned_reservoirs(spark, sf, swap, threaded):
    df = X.doc_dense(spark, sf).repartitionByRange(3, F.desc("y"), "id").sortWithinPartitions(F.desc("y"), "id").persist()
    n = df.count()
    w, history = mrs.fit_partitioned(df, LR, X.D, 30, 3, lambda e: 0.5 / e**0.5, threaded=threaded, swap=swap)
    assert [h["rows"] for h in history] == [n] * 3
    assert [h["buffered"] for h in history] == ([30] * 3 if swap == "pass" else [0] * 3)
    assert loop.objective(df, LR, w) < history[1]["loss_start"] < history[0]["loss_start"] * 3
    with pytest.raises(ValueError):
        mrs.fit_partitioned(df, LR, X.D, 1 << 30, 1, lambda e: 0.1, swap="pass")
    df.unpersist()


def test_reservoirs_carried_over_a_pass_are_the_serial_method(spark, sf):
    """One partition against plain loops: step on what the reservoir lets go, and on the reservoir of the pass before."""
    df = X.doc_dense(spark, sf).repartition(1).sortWithinPartitions(F.desc("y"), "id").persist()
    data = [(np.array(r.x), r.y) for r in df.collect()]
    m, w, before = 10, np.zeros(X.D), []
    for e in (1, 2):
        rng, held, j = np.random.default_rng([42, e, 0]), [], 0
        for p, (x, y) in enumerate(data, 1):
            s = p - 1 if p <= m else int(rng.integers(p))
            if p > m:
                a, b = held[s] if s < m else (x, y)
                w = w + 0.2 * LR.one()(float(w @ a), b) * a
            if s < m:
                held[s:s + 1] = [(x, y)]
            if before:
                a, b = before[j]
                w, j = w + 0.2 * LR.one()(float(w @ a), b) * a, (j + 1) % m
        before = held
    got, _ = mrs.fit_partitioned(df, LR, X.D, m, 2, lambda e: 0.2, swap="pass")
    assert np.allclose(got, w)
    df.unpersist()
