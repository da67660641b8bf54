"""Queries of streams, user-defined functions and the SQL front end."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from .. import sqlapi
from ..functions import vectors as V
from ..operators.tasks import LR, SVM
from ..sources.tables import table
from ..streaming import online, windows
from . import fixtures as X
from . import sqlfold as S
from .registry import query
from .training import MODEL, _epoch_sql, keyed


@query("SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf):
    return windows.replay(windows.tumbling(windows.events(spark, sf)))


@query("SELECT strftime(b + INTERVAL 30 MINUTE * o, '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS b FROM events), (VALUES (0), (-1)) t(o) GROUP BY 1")
def stream_sliding(spark, sf):
    return windows.replay(windows.sliding(windows.events(spark, sf)))


@query("WITH g AS (SELECT user_id, ts, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 6 HOUR)::INT AS new FROM events), s AS (SELECT user_id, sum(coalesce(new, 0)) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM g) SELECT user_id, count(*) AS n FROM s GROUP BY user_id, s")
def stream_session(spark, sf):
    return windows.replay(windows.sessions(windows.events(spark, sf)))


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf):
    return windows.replay(windows.first_seen(windows.events(spark, sf)), "append")


@query("SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark, sf):
    static = table(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    joined = windows.events(spark, sf).join(static, F.col("user_id") == F.col("c_custkey"))
    return windows.replay(joined.groupBy("c_mktsegment").agg(F.count("*").alias("n")))


@query("""SELECT strftime(start, '%Y-%m-%d %H:%M') AS start, event_type, n, total FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2)
 WHERE start + INTERVAL 1 HOUR <= (SELECT date_trunc('millisecond', max(ts)) FROM events) - INTERVAL 2 HOUR""")
def stream_late_drop(spark, sf):
    """Closed windows only: those that the watermark has passed."""
    return windows.replay(windows.tumbling(windows.events(spark, sf)), "append")


_SQL_STREAM = "SELECT event_id AS id, [ln(1 + value), hour(ts) / 24.0::DOUBLE, 1.0::DOUBLE] AS x, CASE WHEN event_type = 'purchase' THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM events"


@query(f"SELECT c.j, c.w, (SELECT count(*) FROM events) AS rows FROM ({S.coords(f'SELECT {S.fold("", LR.sql_move, 0.05, 3)} AS w FROM ({S.keyed(_SQL_STREAM, "id")})', 3)}) c")
def online_lr(spark, sf):
    """Purchases against other events, learnt from the stream batch by batch."""
    x = F.array(F.log1p("value"), F.hour("ts") / 24.0, F.lit(1.0))
    stream = windows.events(spark, sf).select(F.col("event_id").alias("k"), x.alias("x"), F.when(F.col("event_type") == "purchase", 1.0).otherwise(-1.0).alias("y"))
    learner = online.learn(stream, online.OnlineLearner(LR, 3, 0.05))
    return spark.createDataFrame([(j, round(float(v), 6) + 0.0, learner.rows) for j, v in enumerate(learner.w)], "j int, w double, rows long")


@query(f"SELECT id, round(1.0 / (1.0 + exp(-list_dot_product({S.MODEL}, x))), 6) AS s FROM ({X.SQL_EMB})")
def udf_sigmoid(spark, sf):
    @F.pandas_udf("double")
    def sigmoid(u: pd.Series) -> pd.Series:
        return 1 / (1 + np.exp(-u))

    return X.emb_half(spark, sf).select("id", F.round(sigmoid(V.dot(V.literal(MODEL), F.col("x"))), 6).alias("s"))


@query(f"SELECT y, round(sum({LR.sql_loss.format(u=f'list_dot_product({S.MODEL}, x)', y='y')}), 6) AS loss FROM ({X.SQL_EMB}) GROUP BY y")
def udaf_loss(spark, sf):
    @F.pandas_udf("double")
    def loss(u: pd.Series, y: pd.Series) -> float:
        return float(np.logaddexp(0, -y * u).sum())

    return X.emb_half(spark, sf).groupBy("y").agg(F.round(loss(V.dot(V.literal(MODEL), F.col("x")), F.col("y")), 6).alias("loss"))


@query(_epoch_sql(LR))
def udtf_train(spark, sf):
    sqlapi.register(spark)
    keyed(X.emb_half(spark, sf)).select("k", "x", "y").createOrReplaceTempView("gf_rows")
    return spark.sql("SELECT j, round(w, 6) + 0D AS w FROM gf_train(TABLE(gf_rows) WITH SINGLE PARTITION ORDER BY (k), 'lr', 0.1D, 1)")


@query(f"SELECT id, round(list_dot_product({S.MODEL}, x), 6) AS margin FROM ({X.SQL_EMB})")
def udtf_predict(spark, sf):
    sqlapi.register(spark)
    X.emb_half(spark, sf).select("id", "x").createOrReplaceTempView("gf_points")
    weights = "array(" + ", ".join(f"{v!r}D" for v in MODEL) + ")"
    return spark.sql(f"SELECT id, round(margin, 6) AS margin FROM gf_predict(TABLE(gf_points), {weights})")


def _svm_sql(epochs=3):
    parts, start = [f"d AS MATERIALIZED ({S.once(X.SQL_EMB)})"], None
    for e in range(1, epochs + 1):
        parts.append(f"w{e} AS MATERIALIZED (SELECT {S.fold('', SVM.sql_move, 0.1, start=start)} AS w FROM d)")
        start = f"(SELECT w FROM w{e})"
    u = f"list_dot_product(w[1:{X.D}], x)"
    return f"WITH {', '.join(parts)} SELECT y, CASE WHEN {u} < 0 THEN -1.0::DOUBLE ELSE 1.0::DOUBLE END AS prediction, count(*) AS n FROM w{epochs}, ({X.SQL_EMB}) GROUP BY 1, 2"


@query(_svm_sql())
def sql_svm_train(spark, sf):
    """The user's call: train a model by names, save it, apply it."""
    from ..sources.files import scratch

    path = scratch(spark, "models")
    X.emb_half(spark, sf).createOrReplaceTempView("gf_labelled")
    sqlapi.svm_train(spark, "papers", "gf_labelled", "x", "y", path=path, ident="id")
    return sqlapi.apply(spark, "papers", path, "gf_labelled", "x").groupBy("y", "prediction").agg(F.count("*").alias("n"))
