"""Measures of accuracy and cost."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .ranks import offsets, sorted_runs


def confusion(df: DataFrame, truth: str = "y", predicted: str = "prediction") -> DataFrame:
    return df.groupBy(F.col(truth).cast("double").alias("truth"), F.col(predicted).cast("double").alias("predicted")).agg(F.count("*").alias("n"))


def _share(condition: Column) -> Column:
    return F.sum(F.when(condition, 1.0).otherwise(0.0))


def classification(df: DataFrame, truth: str = "y", predicted: str = "prediction") -> DataFrame:
    """(metric, value): accuracy, precision, recall and F1 of class +1."""
    t, p = F.col(truth) > 0, F.col(predicted) > 0
    sums = df.agg(_share(t == p).alias("right"), _share(t & p).alias("tp"), _share(p).alias("pp"), _share(t).alias("tt"), F.count("*").cast("double").alias("n"))
    safe = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    precision, recall = safe(F.col("tp"), F.col("pp")), safe(F.col("tp"), F.col("tt"))
    rows = F.array(
        F.struct(F.lit("accuracy").alias("metric"), safe(F.col("right"), F.col("n")).alias("value")),
        F.struct(F.lit("f1").alias("metric"), safe(2 * F.col("tp"), F.col("pp") + F.col("tt")).alias("value")),
        F.struct(F.lit("precision").alias("metric"), precision.alias("value")),
        F.struct(F.lit("recall").alias("metric"), recall.alias("value")),
    )
    return sums.select(F.explode(rows).alias("r")).select("r.metric", F.round("r.value", 6).alias("value"))


def auc(df: DataFrame, truth: str = "y", score: str = "score") -> DataFrame:
    """Area under the ROC curve from counts per distinct score, by sorted ranges of scores with the counts of all earlier ranges."""
    counts = df.groupBy(F.col(score).alias("s")).agg(_share(F.col(truth) > 0).alias("pos"), _share(F.col(truth) <= 0).alias("neg"))
    counts, _ = sorted_runs(counts, [F.col("s")], "run", "at")
    sizes = dict(sorted(counts.groupBy("run").agg(F.sum("neg")).collect()))  # one row for each range
    inside = F.sum("neg").over(Window.partitionBy("run").orderBy("s").rowsBetween(Window.unboundedPreceding, -1))
    below = offsets(sizes, "run").cast("double") + F.coalesce(inside, F.lit(0.0))
    area = counts.select("pos", "neg", (F.col("pos") * (below + 0.5 * F.col("neg"))).alias("a"))
    return area.agg(F.round(F.sum("a") / (F.sum("pos") * F.sum("neg")), 6).alias("auc"))


def log_loss(df: DataFrame, truth: str = "y", probability: str = "score") -> DataFrame:
    p = F.when(F.col(truth) > 0, F.col(probability)).otherwise(1.0 - F.col(probability))
    return df.agg(F.round(F.avg(-F.log(F.greatest(p, F.lit(1e-15)))), 6).alias("logloss"))


def errors(df: DataFrame, truth: str, predicted: str) -> DataFrame:
    e = F.col(truth) - F.col(predicted)
    return df.agg(F.round(F.sqrt(F.avg(e * e)), 6).alias("rmse"), F.round(F.avg(F.abs(e)), 6).alias("mae"))


def timed(run: Callable[[], object], n: int = 3) -> float:
    """Mean seconds of n runs after one to warm up."""
    run()
    start = time.time()
    for _ in range(n):
        run()
    return (time.time() - start) / n


def overhead(task_seconds: float, null_seconds: float) -> float:
    """Per cent above the NULL aggregate."""
    return 100 * (task_seconds - null_seconds) / null_seconds


def epochs_to(history: DataFrame, best: str = "best", tolerance: float = 1e-3) -> DataFrame:
    """(run, epochs): the first epoch of each run whose loss is within the tolerance of its `best`."""
    good = F.col("loss") <= F.col(best) * (1 + tolerance)
    return history.groupBy("run").agg(F.min(F.when(good, F.col("epoch"))).alias("epochs"))


def relative_objective(history: DataFrame, base: str) -> DataFrame:
    """(run, epoch, ratio): each run's loss over that of run `base` in the same epoch."""
    ref = history.where(F.col("run") == base).select("epoch", F.col("loss").alias("ref"))
    return history.join(F.broadcast(ref), "epoch").select("run", "epoch", F.round(F.col("loss") / F.col("ref"), 6).alias("ratio"))


def speedup(times: DataFrame) -> DataFrame:
    """(scheme, threads, speedup) from (scheme, threads, seconds)."""
    one = times.where("threads = 1").select("scheme", F.col("seconds").alias("one"))
    return times.join(one, "scheme").select("scheme", "threads", F.round(F.col("one") / F.col("seconds"), 6).alias("speedup"))


def scaling_exponent(points: DataFrame, size: str, seconds: str) -> DataFrame:
    """The slope of log seconds over log size; 1 is linear."""
    return points.agg(F.round(F.regr_slope(F.log(seconds), F.log(size)), 6).alias("exponent"))
