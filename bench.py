"""Headline runs at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Times are of warm runs, as in the published tables: `epoch` entries are one pass
over stored, ordered data without the shuffle, `null` is the same pass with a task
that computes nothing, and `to tolerance` entries train until the objective is
within 0.1 % of the optimum.
"""

from __future__ import annotations

import json
import os
import sys
import tempfile
import time

import numpy as np

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "8"))
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from gradfold.operators import baselines, factor, folds, loop, merge, metrics, mrs, parallel, sparse, steps, stop
    from gradfold.operators.ordering import Clustered, ShuffleAlways, ShuffleOnce
    from gradfold.operators.tasks import LR, NULL, SVM
    from gradfold.plans import fixtures as X
    from gradfold.plans import orders, relational, training

    shared = tempfile.mkdtemp(prefix="gradfold-bench-")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(cpus))
        .config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.checkpoint.dir", f"{shared}/shared")
        .config("spark.sql.warehouse.dir", f"{shared}/warehouse")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def timed(name, run, warm=True, n=3):
        if warm:
            run()
        start = time.time()
        for _ in range(n):
            out = run()
        times[name] = round((time.time() - start) / n, 4)
        return out

    def placed(df, parts):
        keyed = df.select(F.xxhash64(F.lit(42), "id").alias("k"), "x", "y")
        out = folds.pack(loop.segments(keyed, parts).sortWithinPartitions("seg", "k")).persist()
        out.count()
        return out

    # single passes over lineitem (the row count of the published dense set at sf0.1)
    dense = X.line_dense(spark, sf)
    d, zero = 5, np.zeros(5)
    by_part = placed(dense, cpus)
    serial = placed(dense, 1)
    for task in (NULL, LR, SVM):
        timed(f"epoch_dense_{task.name}_serial", lambda task=task: folds.fold_packed(serial, task, zero, 0.01).collect())
        timed(f"epoch_dense_{task.name}_averaged", lambda task=task: merge.average(folds.fold_packed(by_part, task, zero, 0.01)).collect())
    timed("loss_dense_lr", lambda: folds.packed_sums(by_part, LR, zero))
    timed("batch_gradient_dense_lr", lambda: folds.packed_sums(by_part, LR, zero, True))

    # single passes over sparse rows: the model is a table, so a pass has its join and its merge by feature
    rows = X.sparse_rows(X.doc_sparse(spark, sf, labelled=False)).withColumn("k", F.xxhash64(F.lit(42), "id")).persist()
    n_sparse = rows.count()
    held = sparse.pack(rows, cpus).persist()
    touched = held.mapInArrow(sparse._features, "seg long, feature long").distinct().repartition(cpus, "seg").persist()
    none = spark.createDataFrame([], "feature long, w double")
    touched.count()
    for task in (NULL, LR, SVM):
        timed(f"epoch_sparse_{task.name}_averaged", lambda task=task: sparse.epoch(held, touched, none, task, 1.0, n_sparse).groupBy("feature").agg(F.sum("w").alias("w")).write.format("noop").mode("overwrite").save())
    timed("shuffle_sparse", lambda: rows.repartition(cpus, "k").sortWithinPartitions("k").write.format("noop").mode("overwrite").save())
    for df in (held, touched, rows):
        df.unpersist()

    # concurrent writers of one model in the memory of this host
    emb_rows = X.emb_half(spark, sf).withColumn("k", F.xxhash64(F.lit(42), "id")).persist()
    for threads in (1, cpus // 2):
        dealt = loop.segments(emb_rows, threads).select("x", "y").persist()
        dealt.count()
        for scheme in parallel.SCHEMES:
            shared_model = parallel.SharedModel(X.D)
            timed(f"shared_{scheme}_{threads}", lambda scheme=scheme, m=shared_model, df=dealt: parallel.shared_epoch(df, LR, m, 0.1, scheme), n=1)
            shared_model.close()
        dealt.unpersist()
    emb_rows.unpersist()

    # shuffle against gradient time
    timed("shuffle_dense", lambda: ShuffleAlways(fast=True).apply(dense, 1).select("k", "x", "y").repartition(cpus, "k").sortWithinPartitions("k").write.format("noop").mode("overwrite").save())

    # training to 0.1 % of the optimum
    emb = X.emb_half(spark, sf).persist()
    best = loop.objective(dense, LR, baselines.newton_lr(dense, d, 5))
    fit = timed("to_tolerance_dense_lr", lambda: loop.fit(dense, LR, d, ShuffleOnce(fast=True), steps.PerEpoch(0.01, 1), cpus, stop=stop.OptGap(best) | stop.MaxEpochs(20)), warm=False, n=1)
    timed("native_dense_lr", lambda: baselines.mllib_lr(dense), warm=False, n=1)
    timed("to_tolerance_dense_svm", lambda: loop.fit(dense, SVM, d, ShuffleOnce(fast=True), steps.PerEpoch(0.01, 1), cpus, stop=stop.RelDrop(1e-3) | stop.MaxEpochs(20)), warm=False, n=1)
    timed("native_dense_svm", lambda: baselines.mllib_svc(dense, 50), warm=False, n=1)

    # order: epochs to twice the optimum
    low = loop.objective(emb, LR, baselines.newton_lr(emb, X.D, 5))
    epochs = {}
    for name, order in (("clustered", Clustered()), ("once", ShuffleOnce()), ("always", ShuffleAlways())):
        run = timed(f"order_{name}", lambda order=order: loop.fit(emb, LR, X.D, order, steps.PerEpoch(1.0), stop=stop.OptGap(low, 0.05) | stop.MaxEpochs(12)), warm=False, n=1)
        epochs[name] = len(run.history)

    # a pass without any shuffle
    clustered = dense.repartitionByRange(cpus, F.desc("y"), "id").sortWithinPartitions(F.desc("y"), "id").select("x", "y").persist()
    clustered.count()
    timed("mrs_epoch_dense", lambda: mrs.fit_partitioned(clustered, LR, d, 60_000, 1, steps.Constant(0.01)), n=1)

    # factorisation: one pass over the ratings
    cells = X.ratings(spark, sf).persist()
    cells.count()
    timed("epoch_lmf_strata", lambda: factor.fit_strata(cells, 8, 1, steps.Constant(0.05), parts=4)[1], warm=False, n=1)
    timed("native_lmf", lambda: baselines.mllib_als(cells, 8, 5)[1], warm=False, n=1)

    for f in (training.igd_lr_epoch_hof, training.igd_lr_model_average, training.crf_epoch, training.lmf_loss, orders.mrs_schedule, orders.catx_epochs, relational.agg_pricing, relational.feat_tfidf, relational.join_orders_lineitem):
        timed(f.__name__, lambda f=f: f(spark, sf).write.format("noop").mode("overwrite").save(), warm=True, n=1)

    rows = dense.count()
    print(
        json.dumps(
            {
                "metric": "headline total",
                "value": round(sum(times.values()), 3),
                "unit": "sec",
                "queries": times,
                "sf": os.path.basename(sf.rstrip("/")),
                "rows": rows,
                "epochs_to_tolerance_dense_lr": len(fit.history),
                "epochs_to_5_percent": epochs,
                "overhead_percent": {f"{data}_{t}_{kind}": round(metrics.overhead(times[f"epoch_{data}_{t}_{kind}"], times[f"epoch_{data}_null_{kind}"]), 1) for data, kind in (("dense", "serial"), ("dense", "averaged"), ("sparse", "averaged")) for t in ("lr", "svm")},
                "speedup_shared": {s: round(times[f"shared_{s}_1"] / times[f"shared_{s}_{cpus // 2}"], 2) for s in parallel.SCHEMES} if cpus > 1 else {},
            }
        )
    )
    spark.stop()


if __name__ == "__main__":
    main()
