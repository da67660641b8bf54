"""Queries of data orders, samples, multiplexed reservoir sampling and the one-dimensional worked example."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions import vectors as V
from ..operators import folds, mrs
from ..operators import sampling as P
from ..operators.ordering import Clustered, LocalShuffle, ShuffleAlways, ShuffleOnce, Stored, WithReplacement
from ..operators.ranks import ranked
from ..operators.tasks import LR
from . import fixtures as X
from . import sqlfold as S
from .registry import query


def _places(spark, sf, order, epoch=1):
    df = order.apply(X.emb_half(spark, sf).select("id", "y"), epoch)
    return df.select("id", F.row_number().over(Window.orderBy("k", "id")).alias("pos"))


def _places_sql(key):
    return f"SELECT id, row_number() OVER (ORDER BY {key}, id)::INT AS pos FROM ({X.SQL_EMB})"


@query(_places_sql("id"))
def order_stored(spark, sf):
    return _places(spark, sf, Stored())


@query(_places_sql("y DESC"))
def order_clustered(spark, sf):
    return _places(spark, sf, Clustered())


@query(_places_sql(H.sql_key("42", "id")))
def order_shuffle_once(spark, sf):
    return _places(spark, sf, ShuffleOnce())


@query(_places_sql(H.sql_key("42", "1", "id")))
def order_shuffle_always_e1(spark, sf):
    return _places(spark, sf, ShuffleAlways(), 1)


@query(_places_sql(H.sql_key("42", "2", "id")))
def order_shuffle_always_e2(spark, sf):
    return _places(spark, sf, ShuffleAlways(), 2)


@query(f"WITH n AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS row FROM ({X.SQL_EMB})), k AS (SELECT unnest(range(1, (SELECT count(*) FROM n) + 1)) AS k) SELECT k AS pos, id FROM k JOIN n ON n.row = {H.sql_number('42', 'k')} % (SELECT count(*) FROM n)")
def order_with_replacement(spark, sf):
    return WithReplacement().apply(X.emb_half(spark, sf).select("id", "y")).select(F.col("k").alias("pos"), "id")


@query(f"SELECT count(*) AS n, sum(id)::BIGINT AS total FROM ({X.SQL_EMB})")
def order_local_shuffle(spark, sf):
    """A permutation inside input splits: the same rows, in another order."""
    return LocalShuffle().apply(X.emb_half(spark, sf).select("id", "y")).agg(F.count("*").alias("n"), F.sum("id").alias("total"))


# samples

_PLACED = f"SELECT id, row_number() OVER (ORDER BY y DESC, id) AS p FROM ({X.SQL_EMB})"
_SLOTTED = f"SELECT id, p, CASE WHEN p <= 50 THEN p - 1 ELSE {H.sql_number('42', 'p')} % p END AS slot FROM ({_PLACED})"


def _slotted(spark, sf, m=50):
    return P.slots(P.positions(X.emb_half(spark, sf).select("id", "y"), [F.desc("y"), F.asc("id")]), m, 42).select("id", "p", "slot")


@query(f"SELECT slot, arg_max(id, p) AS id FROM ({_SLOTTED}) WHERE slot < 50 GROUP BY slot")
def reservoir_sample(spark, sf):
    return P.reservoir(_slotted(spark, sf), 50).select("slot", "id")


@query(f"SELECT * FROM (SELECT p AS pos, CASE WHEN slot < 50 THEN lag(id) OVER (PARTITION BY slot ORDER BY p) ELSE id END AS id FROM ({_SLOTTED})) WHERE id IS NOT NULL")
def reservoir_drops(spark, sf):
    return P.drops(_slotted(spark, sf), 50).select(F.col("at").alias("pos"), "id")


@query(f"SELECT id FROM ({X.SQL_EMB}) ORDER BY {H.sql_key('42', 'id')}, id LIMIT 50")
def bottom_m_sample(spark, sf):
    return P.bottom_m(X.emb_half(spark, sf).select("id"), 50)


@query(f"SELECT id FROM ({X.SQL_EMB}) WHERE {H.sql_number('42', 'id')} / 4294967296.0::DOUBLE < 0.1")
def bernoulli_hash_sample(spark, sf):
    return P.bernoulli(X.emb_half(spark, sf).select("id"), 0.1)


@query(f"SELECT id, y FROM ({X.SQL_EMB}) WHERE {H.sql_number('42', 'id')} / 4294967296.0::DOUBLE < CASE WHEN y > 0 THEN 0.2 ELSE 0.05 END")
def stratified_sample(spark, sf):
    return P.stratified(X.emb_half(spark, sf).select("id", "y"), {1.0: 0.2, -1.0: 0.05}, "y")


@query(S.coords(f"SELECT {S.fold('', LR.sql_move, 0.1)} AS w FROM (SELECT slot AS k, list_append(x, y) AS r FROM (SELECT slot, arg_max(id, p) AS id FROM ({_SLOTTED}) WHERE slot < 50 GROUP BY slot) JOIN ({X.SQL_EMB}) USING (id))"))
def igd_lr_subsample(spark, sf):
    """One epoch on the reservoir only."""
    held = reservoir_sample(spark, sf).join(X.emb_half(spark, sf), "id").select(F.col("slot").alias("k"), "x", "y")
    return folds.coordinates(folds.fold_catalyst(held, LR, [0.0] * X.D, 0.1))


# multiplexed reservoir sampling, buffer 5, two epochs, one memory step a row; the SQL is for fifty rows, in tests

SQL_SCHEDULE = f"""WITH placed AS (SELECT id, row_number() OVER (ORDER BY y DESC, id) AS p FROM ({X.SQL_TINY})), every AS (SELECT e::INT AS epoch, id, p FROM placed, range(1, 3) t(e)),
 slotted AS (SELECT *, CASE WHEN p <= 5 THEN p - 1 ELSE {H.sql_number('42 + epoch', 'p')} % p END AS slot FROM every),
 io AS (SELECT epoch, p, 0 AS sub, 'io' AS worker, CASE WHEN slot < 5 THEN lag(id) OVER (PARTITION BY epoch, slot ORDER BY p) ELSE id END AS id FROM slotted),
 buffer AS (SELECT epoch + 1 AS epoch, slot, arg_max(id, p) AS id FROM slotted WHERE slot < 5 GROUP BY 1, 2),
 mem AS (SELECT e.epoch, e.p, 1 AS sub, 'memory' AS worker, b.id FROM every e JOIN buffer b ON b.epoch = e.epoch AND b.slot = (e.p - 1) % 5)
 SELECT epoch, p, sub, worker, id FROM io WHERE id IS NOT NULL UNION ALL SELECT epoch, p, sub, worker, id FROM mem"""


def scheduled(df):
    return mrs.schedule(df, [F.desc("y"), F.asc("id")], 5, 2)


@query()
def mrs_schedule(spark, sf):
    return scheduled(X.emb_half(spark, sf)).select("epoch", "p", "sub", "worker", "id")


SQL_MRS = S.coords(f"SELECT {S.fold('', LR.sql_move, 0.1)} AS w FROM (SELECT (epoch, p, sub) AS k, list_append(x, y) AS r FROM ({SQL_SCHEDULE}) JOIN ({X.SQL_TINY}) USING (id))")


def mrs_epochs(df):
    steps = scheduled(df).select(F.struct("epoch", "p", "sub").alias("k"), "x", "y")
    return folds.coordinates(folds.fold_catalyst(steps, LR, [0.0] * X.D, 0.1))


@query()
def igd_lr_mrs(spark, sf):
    return mrs_epochs(X.emb_half(spark, sf))


@query()
def igd_lr_mrs_partitioned(spark, sf):
    """Streaming buffers in every partition of the clustered table, models averaged by epoch."""
    df = X.emb_half(spark, sf).repartitionByRange(4, F.desc("y"), "id").sortWithinPartitions(F.desc("y"), "id")
    w, history = mrs.fit_partitioned(df, LR, X.D, 50, 3, lambda e: 0.1 / e**0.5, swap="pass")
    return spark.createDataFrame([(h["epoch"], float(h["loss_start"]), h["rows"]) for h in history], "epoch int, loss double, rows long")


# the worked example: x = 1, targets +1 then -1, over the rows of a table


@query(X.SQL_CATX)
def catx_data(spark, sf):
    return X.catx(spark, sf).select("id", "y")


_FIRST = f"SELECT y, row_number() OVER (ORDER BY y DESC, id) AS j FROM (SELECT *, row_number() OVER (PARTITION BY y ORDER BY id) AS n FROM ({X.SQL_CATX})) WHERE n <= 5"


@query(f"SELECT k::INT AS k, round(pow(0.9::DOUBLE, k) + 0.1::DOUBLE * sum(pow(0.9::DOUBLE, k - j) * y), 9) AS w FROM range(1, 11) s(k) JOIN ({_FIRST}) ON j <= k WHERE k <= (SELECT count(*) FROM ({_FIRST})) GROUP BY k")
def catx_trace(spark, sf):
    """The model after each of ten steps, over the first five rows of each class, by the fold; the oracle is the closed form."""
    classes = [X.catx(spark, sf).where(F.col("y") == y).orderBy("id").limit(5) for y in (1.0, -1.0)]
    rows = classes[0].union(classes[1]).withColumn("k", F.struct(-F.col("y"), "id")).agg(folds.sorted_rows("k", "x", "y").alias("rows"))
    trace = F.aggregate("rows", F.array(F.lit(1.0)), lambda t, r: F.array_append(t, V.let(F.element_at(t, -1), lambda w: w - 0.1 * (w - r["y"]))))
    return rows.select(F.posexplode(trace).alias("k", "w")).where("k > 0").select("k", F.round("w", 9).alias("w"))


_CLUSTERED = f"SELECT list(y ORDER BY y DESC, id) AS ys, least(0.01::DOUBLE, 10.0::DOUBLE / count(*)) AS a FROM ({X.SQL_CATX})"


@query(f"SELECT round(list_reduce(ys, lambda w, y: w - a * (w - y), 1.0::DOUBLE), 9) AS w FROM ({_CLUSTERED})")
def catx_closed_form(spark, sf):
    """One clustered epoch with a step of 10 over the rows as a sum that needs no order of evaluation; the oracle is the fold."""
    placed, n = ranked(X.catx(spark, sf).select("id", "y"), [F.desc("y"), F.asc("id")], "pos")
    a = min(0.01, 10.0 / max(1, n))
    y = F.col("y") * F.pow(F.lit(1 - a), n - 1 - F.col("pos"))
    return placed.agg(F.round(F.lit((1 - a) ** n) + a * F.sum(y), 9).alias("w"))


@query(f"""WITH RECURSIVE c AS ({_CLUSTERED}), e AS (SELECT 0 AS epoch, 1.0::DOUBLE AS w UNION ALL SELECT epoch + 1, list_reduce(ys, lambda m, y: m - a * (m - y), w) FROM e, c WHERE epoch < 10)
 SELECT epoch, round(w, 9) AS w FROM e WHERE epoch > 0""")
def catx_clustered_map(spark, sf):
    """The clustered epoch as one affine map, from the sizes of both classes, iterated."""
    sizes = X.catx(spark, sf).agg(F.count_if(F.col("y") > 0).alias("p"), F.count_if(F.col("y") < 0).alias("m"))
    keep = 1 - F.least(F.lit(0.01), 10.0 / (F.col("p") + F.col("m")))
    maps = sizes.select(F.pow(keep, F.col("p")).alias("q"), F.pow(keep, F.col("m")).alias("r"))
    epoch = lambda t, e: F.array_append(t, (F.element_at(t, -1) * F.col("q") + 1 - F.col("q")) * F.col("r") - (1 - F.col("r")))
    states = F.aggregate(F.sequence(F.lit(1), F.lit(10)), F.array(F.lit(1.0)), epoch)
    return maps.select(F.posexplode(states).alias("epoch", "w")).where("epoch > 0").select("epoch", F.round("w", 9).alias("w"))


EPOCHS = 100


def _epochs_needed(rows):
    """(run, epochs) from rows (run, pos from 1, y), until the model is near the mean of y: each epoch is an affine map made by sums, and the maps are then chained."""
    n = rows.groupBy("run").agg(F.count("*").alias("n"), F.avg("y").alias("mean"))

    def sums(batches):
        for b in batches:
            for run in pc.unique(b.column(0)):
                part = b.filter(pc.equal(b.column(0), run))
                pos, y, size = (part.column(i).to_numpy() for i in (1, 2, 3))
                a = min(0.1, 100.0 / size[0]) * 0.9 ** np.arange(EPOCHS)
                q = a * (y @ np.exp(np.outer(size[0] - pos, np.log1p(-a))))
                yield pa.RecordBatch.from_arrays([pa.array([run.as_py()] * EPOCHS), pa.array(range(1, EPOCHS + 1), pa.int32()), pa.array((1 - a) ** size[0]), pa.array(q), pa.array([part.column(4)[0].as_py()] * EPOCHS)], names=["run", "e", "p", "q", "mean"])

    each = rows.select("run", "pos", "y").join(F.broadcast(n), "run").select("run", "pos", "y", "n", "mean")
    each = each.mapInArrow(sums, "run string, e int, p double, q double, mean double")
    maps = each.groupBy("run", "e").agg(F.first("mean").alias("mean"), F.first("p").alias("p"), F.sum("q").alias("q"))
    chained = maps.groupBy("run").agg(F.first("mean").alias("mean"), F.sort_array(F.collect_list(F.struct("e", "p", "q"))).alias("m"))
    start = F.struct(F.lit(1.0).alias("w"), F.lit(0).alias("e"))
    near = lambda w: (w - F.col("mean")) * (w - F.col("mean")) < 0.001
    last = F.aggregate("m", start, lambda s, r: F.when(s["e"] > 0, s).otherwise(V.let(s["w"] * r["p"] + r["q"], lambda w: F.struct(w.alias("w"), F.when(near(w), r["e"]).otherwise(0).alias("e")))))
    return chained.select("run", F.nullif(last["e"], F.lit(0)).alias("epochs"))


_RUNS = f"SELECT 'clustered' AS run, row_number() OVER (ORDER BY y DESC, id) AS pos, y FROM c UNION ALL SELECT 'random', row_number() OVER (ORDER BY {H.sql_key('42', 'id')}, id), y FROM c"


@query(f"""WITH RECURSIVE c AS ({X.SQL_CATX}), r AS ({_RUNS}),
 l AS (SELECT run, list(y ORDER BY pos) AS ys, avg(y) AS mean, least(0.1::DOUBLE, 100.0::DOUBLE / count(*)) AS a FROM r GROUP BY run),
 w AS (SELECT run, 0 AS e, 1.0::DOUBLE AS w, mean FROM l UNION ALL SELECT w.run, e + 1, list_reduce(ys, lambda m, y: m - a * pow(0.9::DOUBLE, e) * (m - y), w), w.mean FROM w JOIN l USING (run) WHERE e < {EPOCHS})
 SELECT run, min(e) FILTER (e > 0 AND (w - mean) * (w - mean) < 0.001) AS epochs FROM w GROUP BY run""")
def catx_epochs(spark, sf):
    base = X.catx(spark, sf)
    runs = base.select(F.lit("clustered").alias("run"), F.lpad(F.when(F.col("y") > 0, "0").otherwise("1"), 32, "0").alias("k"), "id", "y")
    runs = runs.union(base.select(F.lit("random"), H.order_key(42, F.col("id")), "id", "y"))
    place = F.row_number().over(Window.partitionBy("run").orderBy("k", "id")).cast("long")
    return _epochs_needed(runs.select("run", place.alias("pos"), "y"))


@query()
def catx_permutations(spark, sf):
    """Epochs needed under twenty random permutations."""
    seeds = spark.range(20).select(F.col("id").cast("string").alias("run"))
    rows = X.catx(spark, sf).select("id", "y").crossJoin(F.broadcast(seeds))
    placed = rows.select("run", F.row_number().over(Window.partitionBy("run").orderBy(H.order_key(F.col("run"), F.col("id")), "id")).alias("pos"), "y")
    return _epochs_needed(placed)

