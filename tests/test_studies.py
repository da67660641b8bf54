"""The studies reproduce what is to be expected of them: which run wins, and how a measure moves with its parameter."""

import threading

import pytest
from pyspark.sql import functions as F
from test_oracles import duck, rows  # noqa: F401

from gradfold.plans import relational, studies
from gradfold.plans import fixtures as X


def test_parallel_schemes_converge_alike(spark, sf):
    got = {(r.run, r.epoch): r for r in studies.parallel_convergence(spark, sf).collect()}
    assert len(got) == 15
    for e in (1, 2, 3):
        assert abs(got["lock", e].loss - got["serial", e].loss) < 1e-4  # a lock makes it the serial method
        assert 0.8 < got["aig", e].ratio < 1.25 and 0.8 < got["nolock", e].ratio < 1.25
    assert got["averaging", 3].loss < got["averaging", 1].loss


def test_reservoirs_beat_subsamples(spark, sf):
    df = X.doc_dense(spark, sf).persist()
    got = {(run, e): v for run, e, v in studies.sample_histories(df, (0.05, 0.2))}
    for share in ("0.05", "0.2"):
        assert got[f"mrs {share}", 3] < got[f"subsample {share}", 3]
        assert got[f"mrs {share}", 3] < got["clustered", 3]
    assert got["subsample 0.2", 3] < got["subsample 0.05", 3] and got["mrs 0.2", 3] < got["mrs 0.05", 3]
    df.unpersist()


def test_shuffled_orders_reach_the_optimum_first(spark, sf):
    got = {r.data_order: r for r in studies.order_study(spark, sf).collect()}
    assert got["once"].reached and got["always"].reached
    assert got["clustered"].epochs >= max(got["once"].epochs, got["always"].epochs)


def test_orders_are_fitted_side_by_side(spark, sf, monkeypatch):
    names, met = list(studies.ORDERS), threading.Barrier(len(studies.ORDERS))

    def fit(rows, *_, **__):
        met.wait(60)  # all are under way at once, or none goes on
        return studies.loop.FitResult(None, [{"steps": rows.count(), "loss": 0.0}])

    monkeypatch.setattr(studies.loop, "fit", fit)
    assert [r.data_order for r in studies.order_study(spark, sf).collect()] == names


def test_dense_documents_are_counted_where_they_are_read(spark, tmp_path):
    odd = [(1, "The the THE quick-brown fox", "en"), (1, "fox é x", "de"), (1, None, "en"), (2, None, "en"), (3, " 12 ", None), (None, "lost", "en"), (4, "Zebra\u212a zebra", None)]
    spark.createDataFrame(odd, "doc_id long, text string, lang string").write.parquet(str(tmp_path / "documents.parquet"))
    made = X.doc_dense(spark, str(tmp_path))
    cells = X.doc_sparse(spark, str(tmp_path), labelled=False).collect()
    want = {}
    for c in cells:
        want.setdefault((c.id, c.y), [0.0] * 64 + [1.0])[c.feature % 64] += 4 * c.value
    got = {(r.id, r.y): r.x for r in made.collect()}
    assert made.count() == len(got) == len(want) and all(got[k] == pytest.approx(x) for k, x in want.items())
    plan = made._jdf.queryExecution().optimizedPlan().toString()
    assert "token" not in plan and "Join" not in plan


def test_growth_ends_at_every_size(spark, sf):
    got = studies.growth_series(spark, sf).orderBy("n").collect()
    assert all(r.completed for r in got) and [r.n for r in got] == [got[0].n * c for c in (1, 2, 4, 8)]


ITEMS = [(1, "words he"), (2, ""), (3, "x"), (4, "ten words he"), (5, None), (6, "quick brown fox jumps"), (7, "   "), (8, "zzz")]
TEXTS = [(1, "concatenate words here"), (2, "The quick brown fox jumps over"), (3, None), (4, ""), (5, "a   b"), (6, "concaten words here"), (7, "quick  brown fox jumps x")]


def test_contained_passages(spark, duck):  # noqa: F811
    docs, items = spark.createDataFrame(TEXTS, "doc_id long, text string"), spark.createDataFrame(ITEMS, "item_id long, text string")
    got = sorted(tuple(r) for r in relational.containing(docs, items).collect())
    assert got == sorted((d, i) for d, t in TEXTS for i, p in ITEMS if t is not None and p is not None and p in t)
    assert relational.containing(docs, items.where("false")).count() == 0
    assert relational.containing(docs.where(F.lit(False)), items).count() == 0


@pytest.mark.parametrize("name", ["overhead_table", "parallel_speedup"])
def test_measured_tables(spark, sf, name):
    got = getattr(studies, name)(spark, sf).collect()
    assert got and all(r.seconds > 0 for r in got)


def test_growth_packs_rows_once(spark, sf, monkeypatch):
    calls, pack = [], studies.folds.pack
    monkeypatch.setattr(studies.folds, "pack", lambda df: calls.append(1) or pack(df))
    studies.growth_series(spark, sf)
    assert len(calls) == 1
