"""The epoch loop: one job for each pass, from the model of the pass before, until a stop rule holds."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from . import folds, prox
from .ordering import Order, ShuffleOnce
from .steps import Constant
from .stop import MaxEpochs, Rule
from .tasks import LinearTask


@dataclass
class FitResult:
    w: np.ndarray
    history: list[dict]
    task: str = ""
    dropped: int = 0
    settings: dict = field(default_factory=dict)


def objective(df: DataFrame, task: LinearTask, w, reg: prox.Prox | None = None) -> float:
    """The sum of the losses of all rows plus the penalty: a commutative aggregate."""
    value = df.agg(F.sum(task.loss_of(V.literal(list(w)), F.col("x"), F.col("y")))).first()[0] or 0.0
    return float(value) + (reg.penalty(np.array(w)) if reg else 0.0)


def gradient(df: DataFrame, task: LinearTask, w) -> DataFrame:
    """(j, g): the full gradient of the loss, partial sums before the exchange."""
    c = V.let(V.dot(V.literal(list(w)), F.col("x")), lambda u: task.move(u, F.col("y")))
    each = df.select((-c).alias("c"), "x").select("c", F.posexplode("x").alias("j", "v"))
    return each.groupBy("j").agg(F.sum(F.col("c") * F.col("v")).alias("g"))


def segments(keyed: DataFrame, parts: int) -> DataFrame:
    """(seg, k, x, y): one partition for each of `parts` segments.

    Segments are the partition numbers themselves: hashing them onto partitions
    would leave some empty and put several in one.
    """
    if parts == 1:
        return keyed.select(F.lit(0).cast("long").alias("seg"), "k", "x", "y").repartition(1)
    seg = F.pmod(F.xxhash64("k"), F.lit(parts))
    return keyed.select(seg.alias("seg"), "k", "x", "y").repartitionById(parts, F.col("seg").cast("int"))


def fit(df: DataFrame, task: LinearTask, d: int, order: Order | None = None, step=None, parts: int = 1, weighting: str = "rows", stop: Rule | None = None, start=None, reg: prox.Prox | None = None, loss: str = "exact", syncs: int = 1, batch: int = 1, state: str = "inplace", sample: Callable[[DataFrame, int], DataFrame] | None = None) -> FitResult:
    """Train on a table (id, x, y).

    The rows are exchanged, sorted and packed once for each order of theirs, and a
    pass reads the packed blocks.  parts: segments of model averaging; 1 is the
    serial fold.  syncs: merges per epoch, each over its share of the blocks.  loss: `exact` scans again after each epoch, `piggyback` takes the loss
    at the epoch's first model from the same pass, so the history lags one epoch.
    sample: takes the rows and the epoch and gives those to train on, in place of all.
    An order that works in place (`LocalShuffle`) exchanges nothing: a segment is an
    input partition then, whatever `parts` says.  Rows with a null in x or y are
    dropped and counted.
    """
    order, step, stop = order or ShuffleOnce(), step or Constant(0.1), stop or MaxEpochs(3)
    clean = df.where(F.col("x").isNotNull() & F.col("y").isNotNull())
    total, n = df.agg(F.count("*"), F.count_if(F.col("x").isNotNull() & F.col("y").isNotNull())).first()
    dropped = total - n
    share = 1.0 / max(1, n)
    w = np.zeros(d) if start is None else np.array(start, float)
    wants = stop.wants_gradient
    history: list[dict] = []
    held = None
    e = steps = 0
    while True:
        e += 1
        t0 = time.time()
        if held is None or order.each_epoch:
            if held is not None:
                held.unpersist()
            rows = order.apply(clean if sample is None else sample(clean, e), e)
            if order.in_place:
                rows = rows.select(F.spark_partition_id().cast("long").alias("seg"), "x", "y")
            else:
                rows = segments(rows, parts).sortWithinPartitions("seg", "k")
            held = folds.pack(rows, max(1 << 12, (1 << 20) // syncs)).persist(StorageLevel.MEMORY_AND_DISK)
            held.count()
        t1 = time.time()
        seen = None
        for sync in range(syncs):
            rows = held if syncs == 1 else held.where(F.pmod("b", F.lit(syncs)) == sync)
            alpha = (lambda k, e=e, s=steps: step(e, s + k)) if getattr(step, "per_step", False) else step(e)
            got = folds.fold_packed(rows, task, w, alpha, reg, share, batch, state).collect()  # one model for each part
            weight = [r.n if weighting == "rows" else 1 for r in got]
            if got:
                w = sum(a * np.array(r.w) for a, r in zip(weight, got, strict=True)) / sum(weight)
                steps += sum(r.steps for r in got)
            seen = sum(r.loss_start for r in got) if seen is None else seen
        t2 = time.time()
        if loss == "exact" or wants:
            total, slope = folds.packed_sums(held, task, w, wants)
        value = total + (reg.penalty(w) if reg else 0.0) if loss == "exact" else (seen or 0.0)
        row = {"epoch": e, "loss": value, "seconds": time.time() - t0, "sec_shuffle": t1 - t0, "sec_fold": t2 - t1, "sec_loss": time.time() - t2, "steps": steps, "w": w.copy()}
        if wants:
            row["grad_norm"] = float(np.linalg.norm(slope))
        history.append(row)
        if stop(history):
            break
    held.unpersist()
    return FitResult(w, history, task.name, dropped, {"order": type(order).__name__, "step": repr(step), "parts": parts, "weighting": weighting})


def history_frame(spark, result: FitResult) -> DataFrame:
    rows = [(h["epoch"], float(h["loss"]), float(h["seconds"]), float(h["sec_shuffle"]), float(h["sec_fold"]), int(h["steps"])) for h in result.history]
    return spark.createDataFrame(rows, "epoch int, loss double, seconds double, sec_shuffle double, sec_fold double, steps long")
