"""Training on sparse rows (id, idx, val, y) with a model that is a table (feature, w).

The rows are packed once, a partition for each segment.  Before an epoch every
segment gets the weights of the features that its rows have, by a join of the model
with the list of them; after it the segments give back those weights, and a join by
feature averages them.  So neither the driver nor any task holds the whole model,
and what is exchanged in an epoch are weights, not rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.files import scratch
from . import prox
from .ordering import Order, ShuffleOnce
from .steps import Constant
from .tasks import LinearTask

BLOCK = "seg long, b int, n int, cuts binary, idx binary, val binary, ys binary"
OUT = "feature long, w double, n long, loss double"


@dataclass
class SparseFit:
    model: DataFrame  # (feature, w)
    history: list[dict]
    parts: int


def labels(spark, parts: int) -> list[int]:
    """Segment numbers that hash partitioning deals one to each of `parts` partitions."""
    found = spark.range(parts * 64).groupBy(F.pmod(F.hash("id"), F.lit(parts)).alias("p")).agg(F.min("id").alias("id")).orderBy("p").collect()
    if len(found) < parts:
        raise RuntimeError("no number was found for some partition")
    return [r.id for r in found]


def pack(keyed: DataFrame, parts: int, segment: Column | None = None, block_cells: int = 1 << 17) -> DataFrame:
    """Blocks of raw numbers of (k, idx, val, y), sorted by k inside `parts` segments, each a partition of its own.

    `segment` gives a row's segment from 0; without it a hash of k does.
    """
    names = labels(keyed.sparkSession, parts)
    at = (F.pmod(F.xxhash64("k"), F.lit(parts)) if segment is None else segment).cast("int") + 1 if parts > 1 else F.lit(1)
    rows = keyed.select(F.element_at(F.array(*(F.lit(n).cast("long") for n in names)), at).alias("seg"), "k", "idx", "val", "y")
    rows = rows.repartition(parts, "seg").sortWithinPartitions("seg", "k").select("seg", "idx", "val", "y")

    def run(batches):
        number = 0
        for b in batches:
            segs, sizes, ys = np.asarray(b.column(0)), np.asarray(b.column(1).value_lengths()).astype(np.int64), np.asarray(b.column(3))
            idx, val = np.asarray(b.column(1).flatten()).astype(np.int64), np.asarray(b.column(2).flatten())
            ends = np.cumsum(sizes)
            cut = np.flatnonzero((np.diff(segs) != 0) | (np.diff((ends - sizes) // block_cells) != 0)) + 1
            out = {c: [] for c in ("seg", "b", "n", "cuts", "idx", "val", "ys")}
            for lo, hi in zip([0, *cut], [*cut, len(segs)], strict=True):
                if lo == hi:
                    continue
                first, last = int(ends[lo] - sizes[lo]), int(ends[hi - 1])
                number += 1
                out["seg"].append(int(segs[lo]))
                out["b"].append(number)
                out["n"].append(int(hi - lo))
                out["cuts"].append(np.append(ends[lo:hi] - sizes[lo:hi], last).astype(np.int64).__sub__(first).tobytes())
                out["idx"].append(idx[first:last].tobytes())
                out["val"].append(val[first:last].astype(np.float64).tobytes())
                out["ys"].append(ys[lo:hi].astype(np.float64).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(out["seg"], pa.int64()), pa.array(out["b"], pa.int32()), pa.array(out["n"], pa.int32()), *(pa.array(out[c], pa.binary()) for c in ("cuts", "idx", "val", "ys"))], names=list(out))

    # mapInArrow forgets how its input is dealt; the second exchange is of a few blocks and is kept
    return rows.mapInArrow(run, BLOCK).repartition(parts, "seg").sortWithinPartitions("seg", "b")


def _row_blocks(table: pa.Table):
    order = np.argsort(table.column("b").to_numpy(), kind="stable")
    cols = [table.column(c).to_pylist() for c in ("cuts", "idx", "val", "ys")]
    for i in order.tolist():
        cuts, idx, val, ys = (np.frombuffer(c[i], t) for c, t in zip(cols, (np.int64, np.int64, np.float64, np.float64), strict=True))
        yield cuts, idx, val, ys


def _row_sums(values: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(values)])
    return total[cuts[1:]] - total[cuts[:-1]]


def _lazy(reg: prox.Prox | None, mu: float, size: int):
    """(touch, spend, settle) of a penalty put off until a coordinate is next read."""
    if reg is None or reg.name == "none":
        return (lambda w, at: None), (lambda t: None), (lambda w: w)
    if reg.name == "l1":
        lazy = prox.LazyL1(size, mu)
        return lazy.touch, lazy.spend, lazy.settle
    if reg.name == "l2":
        total, seen = [0.0], np.zeros(size)

        def touch(w, at):
            w[at] *= np.exp(seen[at] - total[0])
            seen[at] = total[0]

        def settle(w):
            w *= np.exp(seen - total[0])
            return w

        return touch, lambda t: total.__setitem__(0, total[0] + np.log1p(2 * t * mu)), settle
    raise ValueError(f"no lazy form of {reg.name}")


def epoch(blocks: DataFrame, touched: DataFrame, model: DataFrame, task: LinearTask, alpha: float, rows: int, reg: prox.Prox | None = None, mu: float = 0.0) -> DataFrame:
    """(seg, feature, w, n, loss): the weights of each segment's features after its rows, in order, from the model's.

    n is the segment's rows and loss its loss at the epoch's first model, both in
    one row of the segment, else 0 and null.
    """
    weights = touched.join(model, "feature", "left").select("seg", "feature", F.coalesce("w", F.lit(0.0)).alias("w"))

    def work(own: pa.Table, mine: pa.Table) -> pa.Table:
        features, w = mine.column("feature").to_numpy(), mine.column("w").to_numpy().copy()
        order = np.argsort(features)
        features, w = features[order], w[order]
        begin, n, loss = w.copy(), 0, 0.0
        touch, spend, settle = _lazy(reg, mu, len(w))
        one, step = task.one(), alpha / max(1, rows)
        for cuts, idx, val, ys in _row_blocks(own):
            at = np.searchsorted(features, idx)
            loss += float(task.loss_np(_row_sums(begin[at] * val, cuts), ys).sum())
            n += len(ys)
            for lo, hi, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), ys.tolist(), strict=True):
                here, v = at[lo:hi], val[lo:hi]
                touch(w, here)
                c = alpha * one(float(w[here] @ v), y)
                if c:
                    w[here] += c * v
                spend(step)
        settle(w)
        counts = np.zeros(len(w), np.int64)
        counts[:1] = n
        losses = [loss if n and not i else None for i in range(min(1, len(w)))] + [None] * max(0, len(w) - 1)
        return pa.table({"feature": pa.array(features), "w": pa.array(w), "n": pa.array(counts), "loss": pa.array(losses, pa.float64())})

    return blocks.groupBy("seg").cogroup(weights.groupBy("seg")).applyInArrow(work, OUT)


def fit(df: DataFrame, task: LinearTask, epochs: int = 3, order: Order | None = None, step=None, parts: int = 1, reg: prox.Prox | None = None, mu: float = 0.0, start: DataFrame | None = None, segment: Column | None = None) -> SparseFit:
    """Train on (id, idx, val, y); features of a row are distinct and in no set order.

    reg: none, or the L1 or L2 penalty of weight `mu`, applied to a feature when it
    is next touched.  A segment that lacks a feature counts as one that left it
    unchanged.  The loss in the history is that of each epoch's first model.  Rows
    with a null in idx, val or y are dropped.
    """
    order, step = order or ShuffleOnce(), step or Constant(1.0)
    spark = df.sparkSession
    clean = df.where("idx is not null and val is not null and y is not null")
    rows = clean.count()
    model = start if start is not None else spark.createDataFrame([], "feature long, w double")
    history, held, touched = [], None, None
    for e in range(1, epochs + 1):
        if held is None or order.each_epoch:
            for old in (held, touched):
                if old is not None:
                    old.unpersist()
            held = pack(order.apply(clean, e), parts, segment).persist(StorageLevel.MEMORY_AND_DISK)
            touched = held.mapInArrow(_features, "seg long, feature long").distinct().repartition(parts, "seg").persist(StorageLevel.MEMORY_AND_DISK)
        path = scratch(spark, "sparse-epoch")
        epoch(held, touched, model, task, step(e), rows, reg, mu).write.parquet(path)
        model, n, loss = merged(spark.read.schema(OUT).parquet(path), model)
        history.append({"epoch": e, "loss_start": loss, "rows": n})
    for old in (held, touched):
        if old is not None:
            old.unpersist()
    return SparseFit(model, history, parts)


def merged(out: DataFrame, model: DataFrame) -> tuple[DataFrame, int, float]:
    """The next model from what all segments gave back (`OUT`), the rows and the loss: a segment that lacks a feature counts with its weight before."""
    spark = out.sparkSession
    n, loss, segments = out.agg(F.sum("n"), F.sum("loss"), F.count("loss")).first()
    totals = out.groupBy("feature").agg(F.sum("w").alias("total"), F.count("*").alias("have"))
    both = totals.join(model.withColumnRenamed("w", "before"), "feature", "full")
    before, all_ = F.coalesce("before", F.lit(0.0)), F.lit(max(1, segments))
    new = F.when(F.col("have").isNull(), before).otherwise((F.col("total") + before * (all_ - F.col("have"))) / all_)
    path = scratch(spark, "sparse-model")
    both.select("feature", new.alias("w")).write.parquet(path)
    return spark.read.schema("feature long, w double").parquet(path), int(n or 0), float(loss or 0.0)


def _features(batches):
    for b in batches:
        for seg, idx in zip(b.column(0).to_pylist(), b.column(4).to_pylist(), strict=True):
            found = np.unique(np.frombuffer(idx, np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(found), seg, np.int64)), pa.array(found)], names=["seg", "feature"])


def loss(df: DataFrame, task: LinearTask, model: DataFrame) -> DataFrame:
    """(n, loss) over sparse rows: margins by a join on features, partial sums before the exchange."""
    cells = df.select("id", "y", F.explode(F.arrays_zip("idx", "val")).alias("c")).select("id", "y", F.col("c.idx").alias("feature"), F.col("c.val").alias("v"))
    margins = cells.join(model, "feature", "left").groupBy("id", "y").agg(F.sum(F.col("v") * F.coalesce("w", F.lit(0.0))).alias("u"))
    return margins.agg(F.count("*").alias("n"), F.sum(task.loss(F.col("u"), F.col("y"))).alias("loss"))
