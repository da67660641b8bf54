"""Queries of the folds, tasks, parallel schemes, baselines and measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions import vectors as V
from ..operators import baselines, chain, factor, folds, loop, merge, metrics, models, parallel, prox, series, softmax, sparse
from ..operators.ordering import Clustered, ShuffleAlways, ShuffleOnce
from ..operators.steps import Constant, PerEpoch
from ..operators.tasks import ABSOLUTE, HUBER, LR, LSQ, NULL, POISSON, SVM
from ..sources.tables import table
from . import fixtures as X
from . import sqlfold as S
from .registry import query

ALPHA = 0.1
MODEL = [(j % 7 - 3) / 10 for j in range(X.D)]


def keyed(df, seed=42):
    return df.withColumn("k", H.order_key(seed, F.col("id")))


def segmented(df, parts=4):
    """Adds k, and seg by a hash of the id."""
    return keyed(df).withColumn("seg", H.number(7, F.col("id")) % parts)


SEG = f", {H.sql_number('7', 'id')} % 4 AS seg"


def _epoch_sql(task, data=X.SQL_EMB, d=X.D, **more):
    return S.coords(f"SELECT {S.fold('', task.sql_move, ALPHA, d, **more)} AS w FROM ({S.once(data)})", d)


@query(_epoch_sql(LR))
def igd_lr_epoch_hof(spark, sf):
    return folds.coordinates(folds.fold_catalyst(keyed(X.emb_half(spark, sf)), LR, [0.0] * X.D, ALPHA))


@query(_epoch_sql(LR))
def igd_lr_epoch_arrow(spark, sf):
    df = keyed(X.emb_half(spark, sf)).withColumn("seg", F.lit(0).cast("long")).repartition(1, "seg")
    return folds.coordinates(folds.fold_arrow(df, LR, np.zeros(X.D), ALPHA))


@query(_epoch_sql(LR))
def igd_lr_epoch_passed(spark, sf):
    df = keyed(X.emb_half(spark, sf)).withColumn("seg", F.lit(0).cast("long")).repartition(1, "seg")
    return folds.coordinates(folds.fold_arrow(df, LR, np.zeros(X.D), ALPHA, state="passed"))


@query(_epoch_sql(SVM))
def igd_svm_epoch(spark, sf):
    return folds.coordinates(folds.fold_catalyst(keyed(X.emb_half(spark, sf)), SVM, [0.0] * X.D, ALPHA))


@query(_epoch_sql(LSQ, X.SQL_PART, 3))
def igd_lsq_epoch(spark, sf):
    return folds.coordinates(folds.fold_catalyst(keyed(X.part_price(spark, sf)), LSQ, [0.0] * 3, ALPHA))


@query(_epoch_sql(HUBER, X.SQL_PART, 3))
def igd_huber_epoch(spark, sf):
    return folds.coordinates(folds.fold_catalyst(keyed(X.part_price(spark, sf)), HUBER, [0.0] * 3, ALPHA))


@query(_epoch_sql(ABSOLUTE, X.SQL_PART, 3))
def igd_absolute_epoch(spark, sf):
    return folds.coordinates(folds.fold_catalyst(keyed(X.part_price(spark, sf)), ABSOLUTE, [0.0] * 3, ALPHA))


SQL_COUNT = "SELECT id, x, abs(y) + 0.5::DOUBLE AS y FROM (SELECT id, x, round(y, 9) AS y FROM (" + X.SQL_PART + "))"


@query(S.coords(f"SELECT {S.fold('', POISSON.sql_move, 0.01, 3)} AS w FROM ({S.once(SQL_COUNT)})", 3))
def igd_poisson_epoch(spark, sf):
    df = X.part_price(spark, sf).withColumn("y", F.abs(F.round("y", 9)) + 0.5)
    return folds.coordinates(folds.fold_catalyst(keyed(df), POISSON, [0.0] * 3, 0.01))


def _share_sql(data):
    return f"(SELECT count(*) FROM ({data}))"


#: For fifty rows, and for the 200 parts of the smallest scale: tests of the operators.
SQL_L1 = S.coords(f"SELECT {S.fold('', LR.sql_move, ALPHA, reg=prox.l1(1.0).sql, t=ALPHA / 50)} AS w FROM ({S.once(X.SQL_TINY)})")
SQL_RIDGE = S.coords(f"SELECT {S.fold('', LSQ.sql_move, ALPHA, 3, reg=prox.l2(1.0).sql, t=ALPHA / 200)} AS w FROM ({S.once(X.SQL_PART)})", 3)


def regularised_epoch(df, task, d, reg):
    """One epoch in which every row has an equal share of the regulariser."""
    return folds.coordinates(folds.fold_catalyst(keyed(df), task, [0.0] * d, ALPHA, reg=reg, share=1 / max(1, df.count())))


@query()
def igd_lr_l1_epoch(spark, sf):
    return regularised_epoch(X.emb_half(spark, sf), LR, X.D, prox.l1(1.0))


@query()
def igd_ridge_epoch(spark, sf):
    return regularised_epoch(X.part_price(spark, sf), LSQ, 3, prox.l2(1.0))


_L = LR.sql_loss.format(u="0.0::DOUBLE", y="y")


def _loss_sql(task, data, w, d=X.D):
    return f"SELECT count(*) AS n, round(sum({task.sql_loss.format(u=f'list_dot_product({w}, x)', y='y')}), 6) AS loss FROM ({data})"


@query(f"""WITH d AS ({S.once(X.SQL_EMB)}), w1 AS (SELECT {S.fold('', LR.sql_move, 0.1)} AS w FROM d),
 w2 AS (SELECT {S.fold('', LR.sql_move, 0.1 / 2**0.5, start='(SELECT w FROM w1)')} AS w FROM d), w3 AS (SELECT {S.fold('', LR.sql_move, 0.1 / 3**0.5, start='(SELECT w FROM w2)')} AS w FROM d),
 m AS (SELECT 1 AS epoch, w FROM w1 UNION ALL SELECT 2, w FROM w2 UNION ALL SELECT 3, w FROM w3)
 SELECT epoch, round(sum({LR.sql_loss.format(u=f'list_dot_product(w[1:{X.D}], x)', y='y')}), 4) AS loss FROM m, ({X.SQL_EMB}) GROUP BY epoch""")
def igd_lr_3epochs(spark, sf):
    fit = loop.fit(X.emb_half(spark, sf), LR, X.D, ShuffleOnce(42), PerEpoch(0.1, 0.5))
    return loop.history_frame(spark, fit).select("epoch", F.round("loss", 4).alias("loss"))


@query(f"""SELECT n, round(a, 6) AS loss_start, round(b, 6) AS loss_progressive FROM (SELECT count(*) AS n, sum({_L}) AS a FROM ({X.SQL_EMB})),
 (SELECT list_reduce(list(r ORDER BY k), lambda a, r: list_concat(list_transform([0.1::DOUBLE * {LR.sql_move.format(u=f'list_dot_product(a[1:{X.D}], r[1:{X.D}])', y=f'r[{X.D + 1}]')}], lambda c: list_transform(list_zip(a[1:{X.D}], r[1:{X.D}]), lambda z: z[1] + c * z[2]))[1], [a[{X.D + 1}] + {LR.sql_loss.format(u=f'list_dot_product(a[1:{X.D}], r[1:{X.D}])', y=f'r[{X.D + 1}]')}]), {S.ZERO})[{X.D + 1}] AS b FROM ({S.once(X.SQL_EMB)}))""")
def igd_lr_piggyback(spark, sf):
    out = folds.fold_progressive(keyed(X.emb_half(spark, sf)), LR, [0.0] * X.D, ALPHA)
    return out.select("n", F.round("loss_start", 6).alias("loss_start"), F.round("loss_progressive", 6).alias("loss_progressive"))


@query(S.coords(f"SELECT seg, {S.fold('', LR.sql_move, ALPHA)} AS w FROM ({S.once(X.SQL_EMB, SEG)}) GROUP BY seg", keys="seg, "))
def igd_lr_per_segment(spark, sf):
    return folds.coordinates(folds.fold_catalyst(segmented(X.emb_half(spark, sf)), LR, [0.0] * X.D, ALPHA, ["seg"]), ["seg"])


def _averaged(spark, sf, task, weighting="rows"):
    df = segmented(X.emb_half(spark, sf)).repartition(4, "seg")
    out = merge.average(folds.fold_arrow(df, task, np.zeros(X.D), ALPHA), weighting)
    return out.select("j", (F.round("w", 6) + F.lit(0.0)).alias("w"))


def _averaged_sql(task, weight="n"):
    return S.average(f"SELECT seg, count(*) AS n, {S.fold('', task.sql_move, ALPHA)} AS w FROM ({S.once(X.SQL_EMB, SEG)}) GROUP BY seg", weight=weight)


@query(_averaged_sql(LR))
def igd_lr_model_average(spark, sf):
    return _averaged(spark, sf, LR)


@query(_averaged_sql(LR, "1.0"))
def igd_lr_model_average_uniform(spark, sf):
    return _averaged(spark, sf, LR, "uniform")


@query(_averaged_sql(SVM))
def igd_svm_model_average(spark, sf):
    return _averaged(spark, sf, SVM)


CLASSES = 10


def classed(spark, sf):
    x = F.array_append(F.col("embedding").cast("array<double>"), F.lit(1.0))
    return table(spark, sf, "embeddings").select(F.col("vec_id").cast("long").alias("id"), x.alias("x"), F.col("label").cast("int").alias("c"))


def softmax_epoch(rows):
    df = keyed(rows).withColumn("seg", F.lit(0).cast("long")).repartition(1)
    w = F.posexplode("w").alias("p", "v")
    return softmax.fold(df, CLASSES, X.D, ALPHA).select(w).select(F.floor(F.col("p") / X.D).cast("int").alias("cls"), (F.col("p") % X.D).alias("j"), (F.round("v", 6) + F.lit(0.0)).alias("w"))


def _softmax_sql():
    d = X.D
    u = "[" + ", ".join(f"list_dot_product(a[{c * d + 1}:{(c + 1) * d}], r[1:{d}])" for c in range(CLASSES)) + "]"
    step = f"list_transform([{u}], lambda u: list_transform([list_transform(u, lambda v: exp(v - list_max(u)))], lambda e: list_transform(a, lambda v, i: v - {ALPHA!r}::DOUBLE * (e[((i - 1) // {d}) + 1] / list_sum(e) - CASE WHEN (i - 1) // {d} = r[{d + 1}] THEN 1 ELSE 0 END) * r[((i - 1) % {d}) + 1]))[1])[1]"
    rows = f"SELECT {H.sql_key('42', 'id')} AS k, list_append(x, c::DOUBLE) AS r FROM (SELECT vec_id::BIGINT AS id, list_append(embedding::DOUBLE[], 1.0::DOUBLE) AS x, label AS c FROM embeddings)"
    return f"SELECT (p // {d})::INT AS cls, (p % {d})::INT AS j, round(v, 6) + 0.0 AS w FROM (SELECT unnest(range(0, {CLASSES * d})) AS p, unnest(w) AS v FROM (SELECT list_reduce(list(r ORDER BY k), lambda a, r: {step}, list_resize(CAST([] AS DOUBLE[]), {CLASSES * d}, 0.0::DOUBLE)) AS w FROM ({rows})))"


@query(_softmax_sql())
def igd_softmax_epoch(spark, sf):
    """Multinomial logistic regression over ten classes, one epoch."""
    return softmax_epoch(classed(spark, sf))


def _sparse_sql(task, parts=1, alpha=1.0):
    """One epoch by inner products: a row's margin is the sum of all earlier steps times its products with their rows."""
    seg = f"{H.sql_number('7', 'id')} % {parts}"
    return f"""WITH c AS MATERIALIZED ({X.SQL_SPARSE}), r AS (SELECT id, y, seg, row_number() OVER (PARTITION BY seg ORDER BY {H.sql_key('42', 'id')}) AS p FROM (SELECT DISTINCT id, y, {seg} AS seg FROM c)),
 d AS MATERIALIZED (SELECT seg, p, feature, value FROM c JOIN r USING (id)),
 g AS (SELECT a.seg, b.p AS p, a.p AS q, sum(a.value * b.value) AS g FROM d a JOIN d b ON a.seg = b.seg AND a.feature = b.feature AND a.p < b.p GROUP BY 1, 2, 3),
 f AS (SELECT r.seg, r.p, r.y, q.p AS q, coalesce(g, 0.0) AS g FROM r JOIN r q ON q.seg = r.seg AND q.p < r.p LEFT JOIN g ON g.seg = r.seg AND g.p = r.p AND g.q = q.p),
 l AS (SELECT r.seg, r.p, [r.y] || coalesce(any_value(m.gs), CAST([] AS DOUBLE[])) AS row FROM r LEFT JOIN (SELECT seg, p, list(g ORDER BY q) AS gs FROM f GROUP BY 1, 2) m ON m.seg = r.seg AND m.p = r.p GROUP BY r.seg, r.p, r.y),
 s AS (SELECT seg, list_reduce(list(row ORDER BY p), lambda a, r: list_append(a, {alpha!r}::DOUBLE * {task.sql_move.format(u="CASE WHEN length(a) = 0 THEN 0.0::DOUBLE ELSE list_dot_product(a, r[2:]) END", y="r[1]")}), CAST([] AS DOUBLE[])) AS steps FROM l GROUP BY seg),
 t AS (SELECT seg, unnest(range(1, length(steps) + 1)) AS p, unnest(steps) AS step FROM s)
 SELECT feature::BIGINT AS feature, round(sum(step * value) / {parts}, 6) + 0.0 AS w FROM d JOIN t USING (seg, p) GROUP BY feature"""


def _sparse(spark, sf, task, parts=1, **more):
    segment = H.number(7, F.col("id")) % parts
    fit = sparse.fit(X.sparse_rows(X.doc_sparse(spark, sf)), task, 1, ShuffleOnce(), Constant(1.0), parts, segment=segment, **more)
    return fit.model.select("feature", (F.round("w", 6) + F.lit(0.0)).alias("w"))


@query(_sparse_sql(LR))
def igd_lr_sparse_epoch(spark, sf):
    """All labelled documents as sparse rows, one epoch in hash order: the weight of each feature."""
    return _sparse(spark, sf, LR)


@query(_sparse_sql(SVM))
def igd_svm_sparse_epoch(spark, sf):
    return _sparse(spark, sf, SVM)


@query(_sparse_sql(LR, 4))
def igd_lr_sparse_average(spark, sf):
    """Four segments, their changes averaged by feature."""
    return _sparse(spark, sf, LR, 4)


@query()
def igd_lr_sparse_l1_epoch(spark, sf):
    """With the lazy L1 penalty; the weights that are not zero after one epoch."""
    return _sparse(spark, sf, LR, reg=prox.l1(0.01), mu=0.01).where("w != 0")


@query()
def igd_svm_sparse_l2_epoch(spark, sf):
    return _sparse(spark, sf, SVM, reg=prox.l2(0.5), mu=0.5)


@query()
def order_sparse_history(spark, sf):
    """Sparse rows by class, shuffled once and shuffled before each epoch: the loss at the first model of each of four epochs."""
    rows, out = X.sparse_rows(X.doc_sparse(spark, sf)).persist(), []
    for name, order in (("clustered", Clustered()), ("once", ShuffleOnce()), ("always", ShuffleAlways())):
        fit = sparse.fit(rows, LR, 4, order, Constant(1.0))
        out += [(name, h["epoch"], round(h["loss_start"], 6)) for h in fit.history]
    rows.unpersist()
    return spark.createDataFrame(out, "data_order string, epoch int, loss double")


_FLAT = "list_concat(" + ", ".join(factor.sql_start("L", str(i), 2) for i in range(5)) + ", " + ", ".join(factor.sql_start("R", str(j), 2) for j in range(7)) + ")"
_A, _B = "(r[1]::INT * 2)", "((5 + r[2]::INT) * 2)"


#: For the 5 x 7 cells: a test of the fold.
SQL_LMF = f"""WITH d AS (SELECT list_reduce(list([i::DOUBLE, j::DOUBLE, m] ORDER BY k), lambda w, r: list_transform([0.1::DOUBLE * (r[3] - (w[{_A} + 1] * w[{_B} + 1] + w[{_A} + 2] * w[{_B} + 2]))],
   lambda c: list_transform(w, lambda v, p: CASE WHEN p > {_A} AND p <= {_A} + 2 THEN v + c * w[{_B} + p - {_A}] WHEN p > {_B} AND p <= {_B} + 2 THEN v + c * w[{_A} + p - {_B}] ELSE v END))[1], {_FLAT}) AS w FROM ({X.SQL_CELLS}))
 SELECT CASE WHEN p < 10 THEN 'L' ELSE 'R' END AS side, (CASE WHEN p < 10 THEN p // 2 ELSE p // 2 - 5 END)::INT AS id, (p % 2)::INT AS k, round(v, 6) + 0.0 AS f FROM (SELECT unnest(range(0, 24)) AS p, unnest(w) AS v FROM d)"""


def cells_epoch(cells):
    out = factor.fold_small(cells, 5, 7, 2, 0.05)
    return out.select("side", "id", F.col("k").cast("int").alias("k"), "f")


@query()
def igd_lmf_epoch(spark, sf):
    """One epoch of stratified blocks over all ratings: the number of factors and the progressive squared error per cell."""
    _checkpoints(spark)
    cells = X.ratings(spark, sf).persist()
    n = cells.count()
    factors, losses = factor.fit_strata(cells, 4, 1, PerEpoch(0.05, 0.25), parts=4)
    out = factors.agg(F.count("*").alias("factors")).select(F.lit(n).alias("cells"), "factors", F.lit(float(np.sqrt(losses[0] / max(1, n)))).alias("rmse"))
    cells.unpersist()
    return out


@query()
def igd_lmf_rank4(spark, sf):
    """Stratified blocks of rank 4 over all ratings: the squared error per cell in each of three epochs."""
    _checkpoints(spark)
    cells = X.ratings(spark, sf).persist()
    n = cells.count()
    _, losses = factor.fit_strata(cells, 4, 3, PerEpoch(0.1, 0.25), parts=4)
    cells.unpersist()
    return spark.createDataFrame([(e + 1, float(np.sqrt(v / max(1, n)))) for e, v in enumerate(losses)], "epoch int, rmse double")


def _checkpoints(spark):
    from ..sources.files import scratch

    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(scratch(spark, "checkpoints"))


def _hash_factors(df, rank=4):
    return factor.initial(df, rank)


SQL_FACTORS = f"SELECT 'L' AS side, i AS id, {factor.sql_start('L', 'i', 4)} AS f FROM (SELECT DISTINCT i FROM r) UNION ALL SELECT 'R', j, {factor.sql_start('R', 'j', 4)} FROM (SELECT DISTINCT j FROM r)"
SQL_SCORED = "SELECT r.i, r.j, r.m, list_dot_product(a.f, b.f) AS p FROM r JOIN f a ON a.side = 'L' AND a.id = i JOIN f b ON b.side = 'R' AND b.id = j"


@query(f"WITH r AS ({X.SQL_RATINGS}), f AS ({SQL_FACTORS}), s AS ({SQL_SCORED}) SELECT count(*) AS n, round(sum((m - p) * (m - p)) + 0.01 * (SELECT sum(list_dot_product(f, f)) FROM f), 6) AS loss FROM s")
def lmf_loss(spark, sf):
    cells = X.ratings(spark, sf)
    return factor.loss(cells, _hash_factors(cells), 0.01)


@query(f"WITH r AS ({X.SQL_RATINGS}), f AS ({SQL_FACTORS}), s AS ({SQL_SCORED}) SELECT i, j, round(p, 6) AS prediction FROM s")
def lmf_predict(spark, sf):
    cells = X.ratings(spark, sf)
    return factor.predict(cells, _hash_factors(cells)).select("i", "j", F.round("prediction", 6).alias("prediction"))


@query(f"WITH r AS ({X.SQL_RATINGS}), f AS ({SQL_FACTORS}), s AS ({SQL_SCORED}) SELECT round(sqrt(avg((m - p) * (m - p))), 6) AS rmse, round(avg(abs(m - p)), 6) AS mae FROM s")
def rmse_lmf(spark, sf):
    cells = X.ratings(spark, sf)
    return metrics.errors(factor.predict(cells, _hash_factors(cells)), "m", "prediction")


# series


_KALMAN = 30


@query(f"""WITH RECURSIVE y AS (SELECT list(y ORDER BY t) AS y, count(*) AS n FROM ({X.SQL_DAILY})),
 s AS (SELECT 0 AS e, list_resize(CAST([] AS DOUBLE[]), n, 0.0::DOUBLE) AS w, y, n FROM y
   UNION ALL SELECT e + 1, list_reduce(list_transform(range(1, n + 1), lambda t: [t::DOUBLE, y[t]]), lambda a, r: list_concat(CASE WHEN r[1] > 2 THEN a[1:r[1]::INT - 2] ELSE CAST([] AS DOUBLE[]) END,
     CASE WHEN r[1] > 1 THEN [a[r[1]::INT - 1] + 2 * 0.3::DOUBLE / sqrt(e + 1) * (a[r[1]::INT] - a[r[1]::INT - 1])] ELSE CAST([] AS DOUBLE[]) END,
     [a[r[1]::INT] - 2 * 0.3::DOUBLE / sqrt(e + 1) * (a[r[1]::INT] - r[2] + a[r[1]::INT] - CASE WHEN r[1] > 1 THEN a[r[1]::INT - 1] ELSE 0.0 END)], a[r[1]::INT + 1:]), w), y, n FROM s WHERE e < {_KALMAN})
 SELECT e AS epoch, round(list_sum(list_transform(range(1, n + 1), lambda t: (w[t] - y[t]) ** 2 + (w[t] - CASE WHEN t > 1 THEN w[t - 1] ELSE 0.0 END) ** 2)), 4) AS loss FROM s WHERE e > 0 AND e % 10 = 0""")
def igd_kalman(spark, sf):
    """Thirty epochs over the daily series, on an executor; the loss after each tenth."""
    rows = X.daily(spark, sf).withColumn("series", F.lit(0))
    return series.fit_smoothing(rows, _KALMAN, PerEpoch(0.3, 0.5), 10).select("epoch", F.round("loss", 4).alias("loss"))


@query(f"""WITH RECURSIVE y AS (SELECT t, y, CASE WHEN t = max(t) OVER () THEN 2.0::DOUBLE ELSE 3.0::DOUBLE END AS d FROM ({X.SQL_DAILY})),
 f AS (SELECT t, -1.0 / d AS c, y / d AS g FROM y WHERE t = 1 UNION ALL SELECT y.t, -1.0 / (y.d + f.c), (y.y + f.g) / (y.d + f.c) FROM f JOIN y ON y.t = f.t + 1),
 b AS (SELECT t, g AS w FROM f WHERE t = (SELECT max(t) FROM y) UNION ALL SELECT f.t, f.g - f.c * b.w FROM b JOIN f ON f.t = b.t - 1)
 SELECT t, round(w, 6) AS w FROM b""")
def kalman_exact(spark, sf):
    import pandas as pd

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t")
        w = series.smooth_exact(pdf.y.to_numpy()[:, None], w0=np.zeros(1))
        return pd.DataFrame({"t": pdf.t, "w": np.round(w[:, 0], 6)})

    return X.daily(spark, sf).withColumn("series", F.lit(0)).groupBy("series").applyInPandas(solve, "t int, w double")


@query(f"SELECT count(*) AS n, round(sum((w - y) ** 2 + (w - p) ** 2), 6) AS loss FROM (SELECT y, 0.5 * y AS w, coalesce(lag(0.5 * y) OVER (ORDER BY t), 0.0) AS p FROM ({X.SQL_DAILY}))")
def kalman_loss(spark, sf):
    return series.smoothing_loss(X.daily(spark, sf).withColumn("w", F.col("y") * 0.5))


@query(f"WITH r AS ({X.SQL_RETURNS}) SELECT x.a, y.a AS b, round(covar_pop(x.r, y.r) * 1e6, 6) AS cov FROM r x JOIN r y ON x.t = y.t AND x.a <= y.a GROUP BY 1, 2")
def portfolio_cov(spark, sf):
    return series.covariance(X.returns(spark, sf))


@query(f"WITH r AS ({X.SQL_RETURNS}), m AS (SELECT a, avg(r) AS m FROM r GROUP BY a), c AS (SELECT t, sum((r - m) / 5) AS c FROM r JOIN m USING (a) GROUP BY t) SELECT round((SELECT avg(c * c) FROM c) - (SELECT sum(m / 5) FROM m), 9) AS objective")
def portfolio_loss(spark, sf):
    r = X.returns(spark, sf)
    mean = r.groupBy("a").agg(F.avg("r").alias("m"))
    by_t = r.join(F.broadcast(mean), "a").groupBy("t").agg(F.sum((F.col("r") - F.col("m")) / 5).alias("c"))
    risk = by_t.agg(F.avg(F.col("c") * F.col("c")).alias("risk"))
    gain = mean.agg(F.sum(F.col("m") / 5).alias("gain"))
    return risk.crossJoin(gain).select(F.round(F.col("risk") - F.col("gain"), 9).alias("objective"))


@query()
def igd_portfolio(spark, sf):
    """Projected steps on monthly returns of five segments; weights, and the exact ones by enumeration."""
    names = _segments(spark, sf)
    wide = X.returns(spark, sf).groupBy("t").pivot("a", names).agg(F.first("r")).dropna()
    rows = wide.select(F.col("t").alias("k"), F.array(*(F.col(f"`{n}`") for n in names)).alias("r")).persist()
    w = series.fit_portfolio(rows, len(names), 60, lambda e: 20 / e**0.5)
    best = series.portfolio_exact(np.array([r.r for r in rows.orderBy("k").collect()]))  # one row a month, for the check only
    rows.unpersist()
    return spark.createDataFrame([(a, float(v), float(b)) for a, v, b in zip(names, w, best, strict=True)], "asset string, w double, exact double")


def _segments(spark, sf):
    return sorted(r[0] for r in table(spark, sf, "customer").select("c_mktsegment").distinct().collect())


# sequences

TAGS = 3


def _fixed_chain():
    emit = np.array([[((f * 3 + k) % 5 - 2) / 10 for k in range(TAGS)] for f in range(14)])
    move = np.array([[((a * 3 + b) % 4 - 1) / 10 for b in range(TAGS)] for a in range(TAGS)])
    return chain.Chain(emit, move)


SQL_TURNS = """SELECT conv_id::VARCHAR AS seq_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS t, least(length(text) // 50, 9) + 1 AS l,
  CASE WHEN right(text, 1) IN ('.', '!') THEN 11 WHEN right(text, 1) = '?' THEN 12 ELSE 13 END AS e,
  CASE role WHEN 'system' THEN 0 WHEN 'user' THEN 1 ELSE 2 END AS g FROM conversations WHERE text IS NOT NULL"""


@query(f"SELECT seq_id, round(count(*) * ln(3.0::DOUBLE), 6) AS loss FROM ({SQL_TURNS}) GROUP BY seq_id")
def crf_loss_zero_model(spark, sf):
    return chain.losses(X.dialogs(spark, sf), chain.Chain.zero(14, TAGS)).select("seq_id", F.round("loss", 6).alias("loss"))


_E = "(({f} * 3 + {k}) % 5 - 2) / 10.0::DOUBLE"
_POT = " + ".join(_E.format(f=f, k="{k}") for f in ("0", "l", "e"))


#: Enumerates all tag paths of four-turn prefixes: a test of the recursion.
SQL_PATHS = f"""WITH RECURSIVE s AS (SELECT * FROM ({SQL_TURNS}) WHERE t <= 4), tags AS (SELECT unnest([0, 1, 2]) AS k),
 p AS (SELECT seq_id, t, k, {_POT.format(k='k')} AS score, (k = g)::INT AS gold FROM s, tags WHERE t = 1
   UNION ALL SELECT p.seq_id, s.t, tags.k, p.score + ((p.k * 3 + tags.k) % 4 - 1) / 10.0::DOUBLE + {_POT.format(k='tags.k')}, p.gold * (tags.k = g)::INT FROM p JOIN s ON s.seq_id = p.seq_id AND s.t = p.t + 1, tags),
 n AS (SELECT seq_id, max(t) AS n FROM s GROUP BY seq_id)
 SELECT seq_id, round(ln(sum(exp(score))) - sum(gold * score), 6) AS loss FROM p JOIN n USING (seq_id) WHERE t = n GROUP BY seq_id"""


def chain_losses(seqs):
    return chain.losses(seqs, _fixed_chain()).select("seq_id", F.round("loss", 6).alias("loss"))


@query()
def crf_brute_force(spark, sf):
    """The loss of a fixed model over whole conversations by the forward recursion; a test enumerates tag paths of prefixes."""
    return chain_losses(X.dialogs(spark, sf))


@query()
def crf_epoch(spark, sf):
    """Two epochs of incremental training on dialogs: the progressive loss."""
    _, losses = chain.fit(X.dialogs(spark, sf), 14, TAGS, 2, PerEpoch(0.2, 0.5))
    return spark.createDataFrame([(e + 1, float(v)) for e, v in enumerate(losses)], "epoch int, loss double")


@query()
def crf_batch(spark, sf):
    """The batch baseline: full-gradient steps on the same sequences."""
    seqs = X.dialogs(spark, sf)
    model, out = chain.Chain.zero(14, TAGS), []
    for e in range(1, 4):
        model, loss = chain.batch_step(seqs, model, 1.0)
        out.append((e, float(loss)))
    return spark.createDataFrame(out, "epoch int, loss double")


@query()
def crf_viterbi(spark, sf):
    model, _ = chain.fit(X.dialogs(spark, sf), 14, TAGS, 2, PerEpoch(0.2, 0.5))
    return chain.decoded(X.dialogs(spark, sf), model)


@query()
def crf_chunking(spark, sf):
    """Two epochs of chunking over sentences with hashed features, the model as a table, four segments averaged: the progressive loss."""
    _, losses = chain.fit_table(X.chunks(spark, sf, 1 << 16), TAGS, 2, PerEpoch(0.1, 0.5), parts=4)
    return spark.createDataFrame([(e + 1, float(v)) for e, v in enumerate(losses)], "epoch int, loss double")


# losses and predictions of a fixed model


@query(_loss_sql(LR, X.SQL_EMB, S.MODEL))
def lr_loss(spark, sf):
    return _loss(X.emb_half(spark, sf), LR, MODEL)


@query(_loss_sql(SVM, X.SQL_EMB, S.MODEL))
def svm_loss(spark, sf):
    return _loss(X.emb_half(spark, sf), SVM, MODEL)


@query(_loss_sql(LSQ, X.SQL_PART, "[0.5::DOUBLE, -0.25::DOUBLE, 0.125::DOUBLE]"))
def lsq_loss(spark, sf):
    return _loss(X.part_price(spark, sf), LSQ, [0.5, -0.25, 0.125])


@query(_loss_sql(HUBER, X.SQL_PART, "[0.5::DOUBLE, -0.25::DOUBLE, 0.125::DOUBLE]"))
def huber_loss(spark, sf):
    return _loss(X.part_price(spark, sf), HUBER, [0.5, -0.25, 0.125])


def _loss(df, task, w):
    return df.agg(F.count("*").alias("n"), F.round(F.sum(task.loss_of(V.literal(w), F.col("x"), F.col("y"))), 6).alias("loss"))


def _model_frame(spark, w=MODEL):
    return spark.range(1).select(V.literal(w).alias("w"))


_U = f"list_dot_product({S.MODEL}, x)"


@query(f"SELECT id, round(1.0 / (1.0 + exp(-({_U}))), 6) AS score, CASE WHEN {_U} < 0 THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END AS prediction FROM ({X.SQL_EMB})")
def lr_predict(spark, sf):
    return models.predict(X.emb_half(spark, sf), _model_frame(spark), LR).select("id", F.round("score", 6).alias("score"), "prediction")


@query(f"SELECT id, CASE WHEN {_U} < 0 THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END AS prediction FROM ({X.SQL_EMB})")
def svm_predict(spark, sf):
    return models.predict(X.emb_half(spark, sf), _model_frame(spark), SVM).select("id", "prediction")


@query("SELECT count(*) AS n FROM embeddings")
def null_aggregate(spark, sf):
    """The fold with a task that does nothing: sees every row and column."""
    df = keyed(X.emb_half(spark, sf)).withColumn("seg", F.lit(0).cast("long")).repartition(1, "seg")
    return folds.fold_arrow(df, NULL, np.zeros(X.D), 0.0).select("n")


@query(S.coords(f"SELECT {S.fold('', LR.sql_move, ALPHA, start=f'list_append({S.MODEL}, 0.0::DOUBLE)')} AS w FROM ({S.once(X.SQL_EMB)})"))
def warm_start_epoch(spark, sf):
    """A model is saved, loaded, and the epoch begins with it."""
    from ..sources.files import scratch

    path = scratch(spark, "models")
    models.save(spark, path, "warm", 1, "lr", MODEL)
    w, _ = models.load(spark, path, "warm")
    return folds.coordinates(folds.fold_catalyst(keyed(X.emb_half(spark, sf)), LR, w.tolist(), ALPHA))


@query("SELECT vec_id::BIGINT AS id, c::INT AS c, CASE WHEN label = c THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM embeddings, range(0, 10) t(c)")
def binarize_ovr(spark, sf):
    e = table(spark, sf, "embeddings")
    return e.select(F.col("vec_id").cast("long").alias("id"), "label", F.explode(F.sequence(F.lit(0), F.lit(9))).alias("c")).select("id", "c", F.when(F.col("label") == F.col("c"), 1.0).otherwise(-1.0).alias("y"))


# proximal maps on formula vectors

VECTOR = [0.9, 0.4, -0.2, 0.3]
_V = "(VALUES (0, 0.9::DOUBLE), (1, 0.4), (2, -0.2), (3, 0.3)) t(j, v)"


def _proxed(spark, p, t=1.0):
    return spark.range(1).select(F.posexplode(p.column(V.literal(VECTOR), t)).alias("j", "v")).select("j", (F.round("v", 6) + F.lit(0.0)).alias("w"))


@query(f"SELECT j::INT AS j, round(sign(v) * greatest(abs(v) - 0.25, 0), 6) + 0.0 AS w FROM {_V}")
def prox_l1(spark, sf):
    return _proxed(spark, prox.l1(0.25))


@query(f"SELECT j::INT AS j, round(v / 1.5, 6) + 0.0 AS w FROM {_V}")
def prox_l2(spark, sf):
    return _proxed(spark, prox.l2(0.25))


_SCALED = "SELECT vec_id::BIGINT AS id, unnest(range(0, len(embedding))) AS j, 4.0::DOUBLE * unnest(embedding::DOUBLE[]) AS v FROM embeddings"


def _proxed_rows(spark, sf, p):
    """(id, j, w): the map of every embedding, scaled by four."""
    x = F.transform(F.col("embedding").cast("array<double>"), lambda v: 4.0 * v)
    rows = table(spark, sf, "embeddings").select(F.col("vec_id").cast("long").alias("id"), x.alias("x"))
    return rows.select("id", F.posexplode(p.column(F.col("x"), 1.0)).alias("j", "v")).select("id", "j", (F.round("v", 6) + F.lit(0.0)).alias("w"))


@query(f"SELECT id, j::INT AS j, round(greatest(0.0, least(0.5, v)), 6) + 0.0 AS w FROM ({_SCALED})")
def prox_box(spark, sf):
    return _proxed_rows(spark, sf, prox.box(0.0, 0.5))


@query(f"SELECT id, j::INT AS j, round(v / greatest(1.0, sqrt(sum(v * v) OVER (PARTITION BY id))), 6) + 0.0 AS w FROM ({_SCALED})")
def prox_ball(spark, sf):
    return _proxed_rows(spark, sf, prox.ball(1.0))


@query(f"""WITH s AS (SELECT j, v, row_number() OVER (ORDER BY v DESC) AS k, sum(v) OVER (ORDER BY v DESC) AS c FROM {_V}), th AS (SELECT (c - 1) / k AS th FROM s WHERE v > (c - 1) / k ORDER BY k DESC LIMIT 1)
 SELECT j::INT AS j, round(greatest(v - th, 0), 6) + 0.0 AS w FROM s, th""")
def prox_simplex(spark, sf):
    return _proxed(spark, prox.simplex())


# orders


def _fit_history(spark, sf, order):
    fit = loop.fit(X.emb_half(spark, sf), LR, X.D, order, PerEpoch(0.1, 0.5))
    return loop.history_frame(spark, fit).select("epoch", F.round("loss", 4).alias("loss"))


def _epochs_sql(keys):
    parts, start = [], None
    for e, key in enumerate(keys, 1):
        parts.append(f"w{e} AS (SELECT {S.fold('', LR.sql_move, 0.1 / e**0.5, start=start)} AS w FROM ({S.keyed(X.SQL_EMB, key)}))")
        start = f"(SELECT w FROM w{e})"
    union = " UNION ALL ".join(f"SELECT {e} AS epoch, w FROM w{e}" for e in range(1, len(keys) + 1))
    return f"WITH {', '.join(parts)}, m AS ({union}) SELECT epoch, round(sum({LR.sql_loss.format(u=f'list_dot_product(w[1:{X.D}], x)', y='y')}), 4) AS loss FROM m, ({X.SQL_EMB}) GROUP BY epoch"


@query(_epochs_sql(["(-y, id)"] * 3))
def igd_lr_clustered(spark, sf):
    return _fit_history(spark, sf, Clustered())


@query(_epochs_sql([H.sql_key("42", "id")] * 3))
def igd_lr_shuffle_once(spark, sf):
    return _fit_history(spark, sf, ShuffleOnce())


@query(_epochs_sql([H.sql_key("42", str(e), "id") for e in (1, 2, 3)]))
def igd_lr_shuffle_always(spark, sf):
    return _fit_history(spark, sf, ShuffleAlways())


# concurrent schemes


def simulated(df, scheme):
    import pyarrow as pa

    df = keyed(df).select("k", "x", "y").repartition(1).sortWithinPartitions("k")

    def run(batches):
        got = [(folds.dense(b.column(1)), np.asarray(b.column(2))) for b in batches]
        w = parallel.simulate(LR, np.concatenate([g[0] for g in got]), np.concatenate([g[1] for g in got]), ALPHA, scheme)
        yield pa.RecordBatch.from_arrays([pa.array([w.tolist()], pa.list_(pa.float64()))], names=["w"])

    return folds.coordinates(df.mapInArrow(run, "w array<double>"))


def _stale_sql(tau, lost="false"):
    d = X.D
    head = f"a[{(tau - 1) * d + 1}:{tau * d}]"
    c = f"0.1::DOUBLE * {LR.sql_move.format(u=f'list_dot_product({head}, r[1:{d}])', y=f'r[{d + 1}]')}"
    new = f"list_transform([{c}], lambda c: list_transform(list_zip(a[1:{d}], r[1:{d}]), lambda z, i: CASE WHEN {lost} THEN z[1] ELSE z[1] + c * z[2] END))[1]"
    rows = f"SELECT k, list_concat(x, [y, (row_number() OVER (ORDER BY k) - 1)::DOUBLE]) AS r FROM (SELECT {H.sql_key('42', 'id')} AS k, x, y FROM ({X.SQL_TINY}))"
    return S.coords(f"SELECT list_reduce(list(r ORDER BY k), lambda a, r: list_concat({new}, a[1:{(tau - 1) * d}]), list_resize(CAST([] AS DOUBLE[]), {tau * d}, 0.0::DOUBLE)) AS w FROM ({rows})")


@query()
def sim_lock_lr(spark, sf):
    return simulated(X.emb_half(spark, sf), "lock")


@query()
def sim_aig_lr(spark, sf):
    return simulated(X.emb_half(spark, sf), "aig")


#: For fifty rows: tests of the simulator.
SQL_STALE = {"lock": _stale_sql(1), "aig": _stale_sql(4), "nolock": _stale_sql(4, f"((i - 1) * 2654435761 + r[{X.D + 2}]::BIGINT * 40503 + 42) % 97 = 0 AND r[{X.D + 2}] % 4 <> 3 AND r[{X.D + 2}] <> 49")}


@query()
def sim_nolock_lr(spark, sf):
    return simulated(X.emb_half(spark, sf), "nolock")


@query()
def shared_nolock_lr(spark, sf):
    """Three epochs of lock-free updates of one shared model by the workers of this host; for a session on one host."""
    df = X.emb_half(spark, sf).withColumn("k", H.fast(42, F.col("id"))).repartition(4, "k").persist()
    model, out = parallel.SharedModel(X.D), []
    try:
        for e in range(1, 4):
            parallel.shared_epoch(df, LR, model, 0.1 / e**0.5)
            out.append((e, loop.objective(df, LR, model.w.copy())))
    finally:
        model.close()
        df.unpersist()
    return spark.createDataFrame(out, "epoch int, loss double")


@query()
def hybrid_lr(spark, sf):
    """Two parts with four lock-free threads each, averaged after each of three epochs: the loss."""
    blocks = folds.pack(segmented(X.emb_half(spark, sf), 2).repartition(2, "seg").sortWithinPartitions("seg", "k")).persist()
    w, out = np.zeros(X.D), []
    for e in range(1, 4):
        got = merge.average(parallel.hybrid_epoch(blocks, LR, w, 0.1 / e**0.5)).collect()
        w = np.array([r.w for r in sorted(got)])
        out.append((e, folds.packed_sums(blocks, LR, w)[0]))
    blocks.unpersist()
    return spark.createDataFrame(out, "epoch int, loss double")


def _minibatch_sql(size=10, rows=50):
    steps, start = [], "list_resize(CAST([] AS DOUBLE[]), " + str(X.D) + ", 0.0::DOUBLE)"
    for b in range(rows // size):
        w = start if b == 0 else f"(SELECT w FROM s{b - 1})"
        g = f"SELECT list(g ORDER BY j) AS g FROM (SELECT j, avg(c * v) AS g FROM (SELECT {LR.sql_move.format(u=f'list_dot_product({w}, x)', y='y')} AS c, unnest(range(0, {X.D})) AS j, unnest(x) AS v FROM d WHERE p // {size} = {b}) GROUP BY j)"
        steps.append(f"s{b} AS (SELECT list_transform(list_zip({w}, g), lambda z: z[1] + 0.5::DOUBLE * z[2]) AS w FROM ({g}))")
    data = f"d AS (SELECT x, y, row_number() OVER (ORDER BY {H.sql_key('42', 'id')}) - 1 AS p FROM ({X.SQL_TINY}))"
    return f"WITH {data}, {', '.join(steps)} SELECT j::INT AS j, round(v, 6) + 0.0 AS w FROM (SELECT unnest(range(0, {X.D})) AS j, unnest(w) AS v FROM s{rows // size - 1})"


def minibatches(df):
    df = keyed(df).withColumn("seg", F.lit(0).cast("long")).repartition(1, "seg")
    return folds.coordinates(folds.fold_arrow(df, LR, np.zeros(X.D), 0.5, batch=10))


@query()
def igd_lr_minibatch(spark, sf):
    """Steps on the mean of ten rows: the variant between row steps and batch gradient."""
    return minibatches(X.emb_half(spark, sf))


@query("WITH t AS (SELECT l_linenumber % 3 AS seg, l_orderkey AS feature, sum(l_discount) AS delta FROM lineitem GROUP BY 1, 2) SELECT feature, round(sum(delta) / 3, 6) AS dense, round(avg(delta), 6) AS touched FROM t GROUP BY feature")
def merge_sparse_deltas(spark, sf):
    """Sparse changes of three parts, the discounts of orders by line number, averaged over all parts and over those that touched an order."""
    deltas = table(spark, sf, "lineitem").groupBy((F.col("l_linenumber") % 3).alias("seg"), F.col("l_orderkey").alias("feature")).agg(F.sum("l_discount").alias("delta"))
    a = merge.average_touched(deltas, 3).withColumnRenamed("delta", "dense")
    b = merge.average_touched(deltas, 3, touched=True).withColumnRenamed("delta", "touched")
    return a.join(b, "feature").select("feature", F.round("dense", 6).alias("dense"), F.round("touched", 6).alias("touched"))


# baselines


@query(f"SELECT j::INT AS j, round(sum(g), 6) + 0.0 AS g FROM (SELECT unnest(range(0, {X.D})) AS j, unnest(list_transform(x, lambda v: -c * v)) AS g FROM (SELECT x, {LR.sql_move.format(u=_U, y='y')} AS c FROM ({X.SQL_EMB}))) GROUP BY j")
def batch_gradient_lr(spark, sf):
    return loop.gradient(X.emb_half(spark, sf), LR, MODEL).select("j", (F.round("g", 6) + F.lit(0.0)).alias("g"))


@query(f"SELECT round(sqrt(sum(g * g)), 6) AS norm FROM (SELECT j, sum(g) AS g FROM (SELECT unnest(range(0, {X.D})) AS j, unnest(list_transform(x, lambda v: -c * v)) AS g FROM (SELECT x, {LR.sql_move.format(u=_U, y='y')} AS c FROM ({X.SQL_EMB}))) GROUP BY j)")
def grad_norm_lr(spark, sf):
    return loop.gradient(X.emb_half(spark, sf), LR, MODEL).agg(F.round(F.sqrt(F.sum(F.col("g") * F.col("g"))), 6).alias("norm"))


def _gd_sql(iters):
    parts = [f"d AS (SELECT x, y FROM ({X.SQL_PART}))", "w0 AS (SELECT [0.0::DOUBLE, 0.0, 0.0] AS w)"]
    for i in range(1, iters + 1):
        g = ", ".join(f"(SELECT avg(x[{j}] * (list_dot_product(w, x) - y)) FROM d, w{i - 1})" for j in (1, 2, 3))
        parts.append(f"g{i} AS (SELECT [{g}] AS g)")
        parts.append(f"w{i} AS (SELECT list_transform(list_zip(w, g), lambda z: z[1] - 0.5::DOUBLE * z[2]) AS w FROM w{i - 1}, g{i})")
    union = " UNION ALL ".join(f"SELECT {i} AS iter, list_dot_product(g, g) AS s FROM g{i}" for i in range(1, iters + 1))
    return f"WITH {', '.join(parts)} SELECT iter, round(sqrt(s) * (SELECT count(*) FROM d), 6) AS norm FROM ({union})"


@query(_gd_sql(3))
def batch_gd_lsq(spark, sf):
    _, norms = baselines.batch_descent(X.part_price(spark, sf).persist(), LSQ, 3, 0.5, 3)
    return spark.createDataFrame([(i + 1, round(v, 6)) for i, v in enumerate(norms)], "iter int, norm double")


@query(f"""WITH d AS (SELECT x, 1.0 / (1.0 + exp(-({_U}))) AS p FROM ({X.SQL_EMB})), e AS (SELECT p * (1 - p) AS s, x, unnest(range(1, {X.D + 1})) AS a FROM d), f AS (SELECT s, x, a, unnest(range(a, {X.D + 1})) AS b FROM e)
 SELECT (a - 1)::INT AS a, (b - 1)::INT AS b, round(sum(s * x[a] * x[b]), 6) + 0.0 AS h FROM f GROUP BY 1, 2""")
def lr_hessian(spark, sf):
    return baselines.hessian(X.emb_half(spark, sf), MODEL).select("a", "b", (F.round("h", 6) + F.lit(0.0)).alias("h"))


@query(f"WITH d AS (SELECT list_append(x, y) AS z FROM ({X.SQL_PART})), e AS (SELECT z, unnest(range(1, 5)) AS a FROM d), f AS (SELECT z, a, unnest(range(a, 5)) AS b FROM e) SELECT (a - 1)::INT AS a, (b - 1)::INT AS b, round(sum(z[a] * z[b]), 6) + 0.0 AS h FROM f GROUP BY 1, 2")
def normal_equations(spark, sf):
    return baselines.normal_sums(X.part_price(spark, sf)).select("a", "b", (F.round("h", 6) + F.lit(0.0)).alias("h"))


@query("SELECT round(regr_slope(p_retailprice, p_partkey % 1000), 6) AS slope, round(regr_intercept(p_retailprice, p_partkey % 1000), 6) AS intercept, round(regr_r2(p_retailprice, p_partkey % 1000), 6) AS r2 FROM part")
def simple_regression(spark, sf):
    x = (F.col("p_partkey") % 1000).cast("double")
    return table(spark, sf, "part").agg(F.round(F.regr_slope("p_retailprice", x), 6).alias("slope"), F.round(F.regr_intercept("p_retailprice", x), 6).alias("intercept"), F.round(F.regr_r2("p_retailprice", x), 6).alias("r2"))


def _objectives(spark, df, task, found):
    return spark.createDataFrame([(name, loop.objective(df, task, w)) for name, w in found], "metric string, value double")


@query()
def mllib_lr(spark, sf):
    df = X.emb_half(spark, sf).persist()
    return _objectives(spark, df, LR, [("native", baselines.mllib_lr(df)), ("newton", baselines.newton_lr(df, X.D)), ("igd", loop.fit(df, LR, X.D, ShuffleOnce(), PerEpoch(1.0, 0.5)).w)])


@query()
def mllib_svc(spark, sf):
    df = X.emb_half(spark, sf).persist()
    return _objectives(spark, df, SVM, [("native", baselines.mllib_svc(df)), ("igd", loop.fit(df, SVM, X.D, ShuffleOnce(), PerEpoch(0.3, 0.5)).w)])


@query()
def mllib_als(spark, sf):
    _, error = baselines.mllib_als(X.ratings(spark, sf), 4, 5)
    return spark.createDataFrame([("squared error", error)], "metric string, value double")


# measures

_PRED = f"SELECT id, y, {_U} AS u, 1.0 / (1.0 + exp(-({_U}))) AS s, CASE WHEN {_U} < 0 THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END AS p FROM ({X.SQL_EMB})"


def _predicted(spark, sf):
    return models.predict(X.emb_half(spark, sf), _model_frame(spark), LR)


@query(f"SELECT y AS truth, p AS predicted, count(*) AS n FROM ({_PRED}) GROUP BY 1, 2")
def confusion_matrix(spark, sf):
    return metrics.confusion(_predicted(spark, sf))


@query(f"""WITH c AS (SELECT avg((p = y)::INT)::DOUBLE AS a, sum((p > 0 AND y > 0)::INT)::DOUBLE AS tp, sum((p > 0)::INT)::DOUBLE AS pp, sum((y > 0)::INT)::DOUBLE AS tt FROM ({_PRED}))
 SELECT unnest(['accuracy', 'f1', 'precision', 'recall']) AS metric, round(unnest([a, 2 * tp / (pp + tt), tp / pp, tp / tt]), 6) AS value FROM c""")
def accuracy(spark, sf):
    return metrics.classification(_predicted(spark, sf))


@query(f"WITH p AS ({_PRED}) SELECT round(avg(CASE WHEN a.s > b.s THEN 1.0 WHEN a.s = b.s THEN 0.5 ELSE 0.0 END), 6) AS auc FROM p a, p b WHERE a.y > 0 AND b.y < 0")
def auc_rank(spark, sf):
    return metrics.auc(_predicted(spark, sf))


@query(f"SELECT round(avg(-ln(greatest(CASE WHEN y > 0 THEN s ELSE 1 - s END, 1e-15))), 6) AS logloss FROM ({_PRED})")
def logloss(spark, sf):
    return metrics.log_loss(_predicted(spark, sf))


HISTORY = [("clustered", 1, 8.0), ("clustered", 2, 4.0), ("clustered", 3, 1.0005), ("once", 1, 2.0), ("once", 2, 1.0002), ("once", 3, 1.0), ("never", 1, 3.0), ("never", 2, 2.5), ("never", 3, 2.25)]
_HISTORY = "(VALUES " + ", ".join(f"('{r}', {e}, {v}::DOUBLE)" for r, e, v in HISTORY) + ") t(run, epoch, loss)"


def _history(spark):
    return spark.sql("SELECT run, epoch, CAST(loss AS DOUBLE) AS loss FROM VALUES " + ", ".join(f"('{r}', {e}, {v})" for r, e, v in HISTORY) + " AS t(run, epoch, loss)")


@query("""WITH h AS (SELECT event_type AS run, date_diff('day', DATE '2024-01-01', ts::DATE) + 1 AS epoch, round(avg(value), 6) AS loss FROM events GROUP BY 1, 2), b AS (SELECT run, min(loss) AS best FROM h GROUP BY run)
 SELECT run, min(epoch) FILTER (loss <= best * 1.1)::INT AS epochs FROM h JOIN b USING (run) GROUP BY run""")
def epochs_to_tolerance(spark, sf):
    """Days as epochs, kinds of events as runs, mean values as losses: the first day within a tenth of the least."""
    days = (F.date_diff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) + 1).alias("epoch")
    history = table(spark, sf, "events").groupBy(F.col("event_type").alias("run"), days).agg(F.round(F.avg("value"), 6).alias("loss"))
    return metrics.epochs_to(history.join(history.groupBy("run").agg(F.min("loss").alias("best")), "run"), tolerance=0.1)


@query(f"SELECT a.run, a.epoch, round(a.loss / b.loss, 6) AS ratio FROM {_HISTORY.replace(' t(', ' a(')} JOIN {_HISTORY.replace(' t(', ' b(')} ON a.epoch = b.epoch AND b.run = 'clustered'")
def relative_objective(spark, sf):
    return metrics.relative_objective(_history(spark), "clustered")


@query("WITH t AS (SELECT event_type AS task, avg(value) AS seconds FROM events GROUP BY 1) SELECT a.task, round(100 * (a.seconds - b.seconds) / b.seconds, 6) AS overhead FROM t a JOIN t b ON b.task = 'view'")
def overhead_formula_check(spark, sf):
    """Per cent of each kind of event's mean value above that of views."""
    means = table(spark, sf, "events").groupBy(F.col("event_type").alias("task")).agg(F.avg("value").alias("seconds"))
    base = means.where("task = 'view'").select(F.col("seconds").alias("base"))
    return means.crossJoin(F.broadcast(base)).select("task", F.round(metrics.overhead(F.col("seconds"), F.col("base")), 6).alias("overhead"))


SPEEDS = [("lock", 1, 20.0), ("lock", 4, 20.0), ("aig", 1, 20.0), ("aig", 4, 6.0), ("nolock", 1, 20.0), ("nolock", 4, 5.0)]
_SPEEDS = ", ".join(f"('{s}', {t}, {v}::DOUBLE)" for s, t, v in SPEEDS)


@query(f"WITH t(scheme, threads, seconds) AS (VALUES {_SPEEDS}) SELECT a.scheme, a.threads, round(b.seconds / a.seconds, 6) AS speedup FROM t a JOIN t b ON a.scheme = b.scheme AND b.threads = 1")
def speedup_table(spark, sf):
    return metrics.speedup(spark.createDataFrame(SPEEDS, "scheme string, threads int, seconds double"))


@query(f"WITH t(scheme, threads, seconds) AS (VALUES {_SPEEDS}) SELECT round(regr_slope(ln(seconds), ln(threads)), 6) AS exponent FROM t WHERE scheme = 'nolock'")
def scaling_exponent(spark, sf):
    return metrics.scaling_exponent(spark.createDataFrame([s for s in SPEEDS if s[0] == "nolock"], "scheme string, threads int, seconds double"), "threads", "seconds")
