"""Sparse training: every penalty against eager numpy, averaging, odd rows, and how segments are dealt."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gradfold.functions import hashing as H
from gradfold.operators import chain, prox, sparse, steps
from gradfold.operators.ordering import Clustered, ShuffleOnce
from gradfold.operators.tasks import LR, SVM
from gradfold.plans import fixtures as X

ROWS = "id long, idx array<long>, val array<double>, y double"


@pytest.fixture(scope="module")
def rows(spark, sf):
    df = X.sparse_rows(X.doc_sparse(spark, sf)).persist()
    yield df
    df.unpersist()


def dense(model):
    w = np.zeros(X.FEATURES)
    for r in model.collect():
        w[r.feature] = r.w
    return w


def eager(rows, task, epochs, alpha, reg=None):
    data = rows.withColumn("k", H.order_key(42, F.col("id"))).orderBy("k").collect()
    w, losses = np.zeros(X.FEATURES), []
    for _ in range(epochs):
        losses.append(sum(float(task.loss_np(w[r.idx] @ np.array(r.val), r.y)) for r in data))
        for r in data:
            w[r.idx] += alpha * task.one()(float(w[r.idx] @ np.array(r.val)), r.y) * np.array(r.val)
            if reg is not None:
                w = reg.array(w, alpha / len(data))
    return w, losses


@pytest.mark.parametrize("task", [LR, SVM])
@pytest.mark.parametrize("reg, mu", [(None, 0.0), (prox.l1(0.01), 0.01), (prox.l2(0.5), 0.5)])
def test_lazy_penalties_equal_eager_ones(rows, task, reg, mu):
    want, losses = eager(rows, task, 2, 1.0, reg)
    fit = sparse.fit(rows, task, 2, ShuffleOnce(), steps.Constant(1.0), 1, reg, mu)
    assert np.allclose(dense(fit.model), want, atol=1e-12)
    assert np.allclose([h["loss_start"] for h in fit.history], losses)
    got = sparse.loss(rows, task, fit.model).first()
    assert got.n == rows.count() and got.loss < losses[0]


def test_each_segment_has_a_partition(spark, rows):
    keyed = rows.withColumn("k", H.fast(42, F.col("id")))
    for parts in (1, 3, 8):
        packed = sparse.pack(keyed, parts)
        got = packed.groupBy(F.spark_partition_id().alias("p")).agg(F.countDistinct("seg").alias("s"), F.sum("n").alias("n")).collect()
        assert len(got) == parts and all(r.s == 1 for r in got) and sum(r.n for r in got) == rows.count()


def test_clustered_order_converges_later(rows):
    a = sparse.fit(rows, LR, 4, Clustered(), steps.Constant(4.0)).history[-1]["loss_start"]
    b = sparse.fit(rows, LR, 4, ShuffleOnce(), steps.Constant(4.0)).history[-1]["loss_start"]
    assert b < a


def test_odd_rows_and_empty_tables(spark):
    df = spark.createDataFrame([(1, [3, 1], [1.0, 2.0], 1.0), (2, [], [], -1.0), (3, None, [1.0], 1.0), (4, [1], [1.0], None), (1, [3, 1], [1.0, 2.0], 1.0)], ROWS)
    fit = sparse.fit(df, LR, 1, ShuffleOnce(), steps.Constant(0.1))
    assert fit.history[0]["rows"] == 3 and {r.feature for r in fit.model.collect()} == {1, 3}
    none = sparse.fit(df.where("false"), LR, 1)
    assert none.model.count() == 0 and none.history[0]["rows"] == 0


def test_chain_with_a_model_table_is_the_dense_one(spark, sf):
    seqs = X.dialogs(spark, sf)
    for mu in (0.0, 0.002):
        dense_model, losses = chain.fit(seqs, 14, 3, 2, steps.PerEpoch(0.2, 0.5), mu)
        model, met = chain.fit_table(seqs, 3, 2, steps.PerEpoch(0.2, 0.5), mu)
        got = {r.feature: r.w for r in model.collect()}
        assert np.allclose(met, losses)
        assert all(np.isclose(got[-1 - (a * 3 + b)], dense_model.move[a, b]) for a in range(3) for b in range(3))
        assert all(np.isclose(w, dense_model.emit[f // 3, f % 3]) for f, w in got.items() if f >= 0)
    _, met = chain.fit_table(seqs, 3, 3, steps.PerEpoch(0.2, 0.5), parts=3)
    assert met[2] < met[0]


def test_chain_fold_is_the_step_of_the_chain(spark):
    """Positions without features, penalties, and weights that leave the range of scaled numbers."""
    rng = np.random.default_rng(5)
    for kinds, alpha, mu, apart in ((1, 0.3, 0.0, 1e-9), (2, 0.3, 0.01, 1e-9), (3, 0.3, 0.0, 1e-9), (3, 900.0, 0.0, 0.05)):
        seqs = []
        for k in range(60):
            n = int(rng.integers(1, 70))
            seqs.append((k, [rng.integers(0, 40, rng.integers(0, 5)).tolist() for _ in range(n)], rng.integers(0, kinds, n).tolist()))
        local, want = chain.Chain.zero(40, kinds), 0.0
        for _, feats, gold in seqs:
            want += local.step(feats, gold, alpha, mu)
        df = spark.createDataFrame(seqs, "k long, feats array<array<int>>, tags array<int>").repartition(3)
        model, met = chain.fit_table(df, kinds, 1, steps.PerEpoch(alpha, 1.0), mu)
        got = {r.feature: r.w for r in model.collect()}
        assert np.allclose(met, [want], rtol=1e-9)
        assert np.allclose([[got[f * kinds + j] for j in range(kinds)] for f in range(40)], local.emit, rtol=1e-7, atol=apart)
        assert np.allclose([[got[-1 - (a * kinds + b)] for b in range(kinds)] for a in range(kinds)], local.move, rtol=1e-7, atol=apart)


def test_chain_with_a_model_table_takes_short_steps(spark):
    """An epoch over 16,000 sequences of 64 positions; it took as long as so many steps in Python before."""
    import time

    from pyspark.sql import functions as F

    rng, own = np.random.default_rng(6), chain.Chain.zero(1000, 3)
    feats, at, gold = rng.integers(0, 1000, 256), np.repeat(np.arange(64), 4), rng.integers(0, 3, 64)
    start = time.perf_counter()
    for _ in range(400):
        own.step_flat(feats, at, gold, 0.01)
    step = (time.perf_counter() - start) / 400
    number = F.transform(F.sequence(F.lit(0), F.lit(255)), lambda i: F.pmod(F.xxhash64("id", i), F.lit(1000)).cast("int"))
    rows = spark.range(16000).select(F.col("id").alias("k"), number.alias("flat"))
    rows = rows.select("k", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda t: F.slice("flat", 4 * t + 1, F.lit(4))).alias("feats"), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda t: F.pmod(F.xxhash64("k", t), F.lit(3)).cast("int")).alias("tags")).persist()
    rows.count()

    def seconds(epochs):
        start = time.perf_counter()
        chain.fit_table(rows, 3, epochs, steps.PerEpoch(0.01, 1.0))
        return time.perf_counter() - start

    seconds(1)
    assert seconds(3) - seconds(1) < 16000 * step
    rows.unpersist()
