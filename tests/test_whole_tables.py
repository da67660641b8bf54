"""Queries take whole tables: against plain loops, and their operators on small fixtures against SQL."""

import numpy as np
import pytest
from test_oracles import duck, rows  # noqa: F401

from gradfold.functions import hashing as H
from gradfold.operators import parallel, prox
from gradfold.operators.tasks import LR, LSQ
from gradfold.plans import fixtures as X
from gradfold.plans import orders, training
from gradfold.plans.registry import QUERIES


def same(df, want):
    assert rows([tuple(r) for r in df.collect()], df.columns) == rows(want.fetchall(), want.columns)


def ordered(df):
    got = training.keyed(df).select("k", "x", "y").orderBy("k").collect()
    return np.array([r.x for r in got]), np.array([r.y for r in got])


def weights(df):
    return np.array([r.w for r in sorted(df.collect())])


FIXTURES = {
    "l1": (lambda df: training.regularised_epoch(df, LR, X.D, prox.l1(1.0)), training.SQL_L1),
    "minibatch": (training.minibatches, training._minibatch_sql()),
    "schedule": (lambda df: orders.scheduled(df).select("epoch", "p", "sub", "worker", "id"), orders.SQL_SCHEDULE),
    "mrs": (orders.mrs_epochs, orders.SQL_MRS),
    **{s: (lambda df, s=s: training.simulated(df, s), sql) for s, sql in training.SQL_STALE.items()},
}


@pytest.mark.parametrize("name", sorted(FIXTURES))
def test_fifty_rows_against_sql(spark, duck, sf, name):  # noqa: F811
    run, sql = FIXTURES[name]
    same(run(X.tiny(spark, sf)), duck.sql(sql))


def test_ridge_against_sql(spark, duck, sf):  # noqa: F811
    same(QUERIES["igd_ridge_epoch"](spark, sf), duck.sql(training.SQL_RIDGE))


def test_shares_follow_the_row_count(spark, sf):
    x, y = ordered(X.emb_half(spark, sf))
    w, t = np.zeros(X.D), 0.1 / len(y)
    for a, b in zip(x, y):
        w = w + 0.1 * float(LR.move_np(a @ w, b)) * a
        w = np.sign(w) * np.maximum(np.abs(w) - t, 0)
    assert len(y) > 50 and np.allclose(weights(QUERIES["igd_lr_l1_epoch"](spark, sf)), w, atol=2e-6)
    half = X.part_price(spark, sf).where("id % 2 = 0")
    x, y = ordered(half)
    w = np.zeros(3)
    for a, b in zip(x, y):
        w = (w + 0.1 * float(LSQ.move_np(a @ w, b)) * a) / (1 + 2 * 0.1 / len(y))  # the penalty is w squared, without a half
    assert np.allclose(weights(training.regularised_epoch(half, LSQ, 3, prox.l2(1.0))), w, atol=2e-6)


def test_every_row_takes_part(spark, sf):
    x, y = ordered(X.emb_half(spark, sf))
    for name in ("lock", "aig", "nolock"):
        assert np.allclose(weights(QUERIES[f"sim_{name}_lr"](spark, sf)), parallel.simulate(LR, x, y, 0.1, name), atol=2e-6)
    w = np.zeros(X.D)
    for at in range(0, len(y), 10):
        a, b = x[at : at + 10], y[at : at + 10]
        w = w + 0.5 * (LR.move_np(a @ w, b)[:, None] * a).mean(axis=0)
    assert np.allclose(weights(QUERIES["igd_lr_minibatch"](spark, sf)), w, atol=2e-6)
    assert QUERIES["mrs_schedule"](spark, sf).select("epoch", "p").distinct().count() >= 2 * len(y) - 10
    assert QUERIES["igd_lr_mrs"](spark, sf).count() == X.D


def test_cells_against_sql(spark, duck, sf):  # noqa: F811
    same(training.cells_epoch(X.small_cells(spark, sf)), duck.sql(training.SQL_LMF))


def test_factorisation_trains_on_all_ratings(spark, duck, sf, monkeypatch):  # noqa: F811
    n, left, right = duck.sql(f"select count(*), count(distinct i), count(distinct j) from ({X.SQL_RATINGS})").fetchall()[0]
    got = QUERIES["igd_lmf_epoch"](spark, sf).first()
    assert (got.cells, got.factors) == (n, left + right)
    rmse = [r.rmse for r in QUERIES["igd_lmf_rank4"](spark, sf).orderBy("epoch").collect()]
    assert len(rmse) == 3 and rmse[2] < rmse[0]
    seen = []
    monkeypatch.setattr(training.baselines, "mllib_als", lambda cells, *a: (None, seen.append(cells.count()) or 0.0))
    QUERIES["mllib_als"](spark, sf)
    assert seen == [n]


def test_chunks_hold_every_token(spark, sf):
    import re

    want = 0
    for r in X.table(spark, sf, "documents").select("text").collect():
        words = [[w for w in re.split(r"[ \t\n\x0b\f\r]+", s) if w] for s in re.split(r"[.!?\n]+", r.text or "")]
        want += sum(len(w) for w in words if len(w) > 1)
    got = [(len(r.feats), len(r.tags), r.seq_id) for r in X.chunks(spark, sf).collect()]
    assert sum(g[0] for g in got) == want and all(a == b and 0 < a <= 64 for a, b, _ in got)
    assert len({g[2] for g in got}) == len(got)


def brute_chunks(rows, most):
    """(seq_id, words, tags) of each sequence by loops."""
    import re

    sentences = {}
    for i, text in rows:
        for n, s in enumerate(re.split(r"[.!?\n]+", text) if text is not None else []):
            w = [x for x in re.split(r"[ \t\n\x0b\f\r]+", re.sub("[A-Z]", lambda m: m[0].lower(), s)) if x]
            if len(w) > 1:
                tagged = [(x.encode(), 0 if not j else 2 if j == len(w) - 1 else 1) for j, x in enumerate(w)]
                sentences.setdefault((i, n // 4), []).append((n, tagged))
    for (i, b), found in sentences.items():
        joined = [t for _, s in sorted(found) for t in s]
        for p in range(0, len(joined), most):
            yield ":".join(map(str, (b, p // most) if i is None else (i, b, p // most))), *zip(*joined[p : p + most])


def test_chunks_of_odd_documents(spark, tmp_path):
    """Repeated and null ids over many small batches, other white space, runs of marks, words of one letter, long texts; the features by Spark's own hash."""
    import random

    rng = random.Random(3)
    words, marks = ["A", "b", "é", "Straße", "日本語", "<", ">", "a\x00b", "\x85", "foo", "zz", "😀a"], [" ", "  ", "\t", "\x0b", "\x0c", "\r", ".", "!?", ". ", "\n", "\r\n", "? ! "]
    rows = [(rng.choice([None, rng.randrange(20), i + 100]), "".join(rng.choice(words) + rng.choice(marks) for _ in range(rng.choice([0, 1, 5, 40, 200])))) for i in range(120)]
    rows += [(1, None), (2, ""), (3, " .\n"), (4, "a b " * 300), (4, "a b " * 300)]
    spark.createDataFrame(rows, "doc_id long, text string").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "3")
    try:
        got = X.chunks(spark, str(tmp_path), 1000, 7).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    want = list(brute_chunks(rows, 7))
    need = {(k, w) for _, own, _ in want for x in own for k, w in ((1, x), (2, x), (3, x), (4, x.decode()[-2:].encode()))} | {(2, b"<"), (3, b">")}
    hashed = spark.createDataFrame([(k, w.decode()) for k, w in need], "k int, w string").selectExpr("k", "w", "xxhash64(1, w) a", "xxhash64(2, w) b", "xxhash64(3, w) c", "xxhash64(4, w) d").collect()
    number = {(r.k, r.w.encode()): [r.a, r.b, r.c, r.d][r.k - 1] % 1000 for r in hashed}
    made = []
    for i, own, tags in want:
        around = [b"<", *own, b">"]
        feats = [[number[1, x], number[2, around[j]], number[3, around[j + 2]], number[4, x.decode()[-2:].encode()]] for j, x in enumerate(own)]
        made.append((i, feats, list(tags)))
    assert sorted((r.seq_id, r.feats, r.tags) for r in got) == sorted(made)


def test_four_turns_against_all_paths(spark, duck, sf):  # noqa: F811
    short = X.dialogs(spark, sf).selectExpr("seq_id", "slice(feats, 1, 4) AS feats", "slice(tags, 1, 4) AS tags")
    same(training.chain_losses(short), duck.sql(training.SQL_PATHS))


def test_losses_of_whole_conversations(spark, sf):
    model, long = training._fixed_chain(), 0
    got = {r.seq_id: r.loss for r in QUERIES["crf_brute_force"](spark, sf).collect()}
    seqs = X.dialogs(spark, sf).collect()
    assert set(got) == {r.seq_id for r in seqs}
    for r in seqs:
        long += len(r.tags) > 4
        emit = np.array([sum(model.emit[f] for f in feats) for feats in r.feats])
        a = emit[0]
        for e in emit[1:]:
            a = e + np.log(np.exp(a[:, None] + model.move).sum(axis=0))
        gold = sum(emit[t][g] for t, g in enumerate(r.tags)) + sum(model.move[g, h] for g, h in zip(r.tags, r.tags[1:]))
        assert abs(got[r.seq_id] - (np.log(np.exp(a).sum()) - gold)) < 2e-6
    assert long
