"""The order-aware aggregate: one pass over the rows of a table, one model step for each.

Three routes give the same numbers.  `catalyst` is an aggregate expression - rows
collected, sorted by key, folded by a lambda - and stays in the JVM; a whole group
is one value there, so it is for groups of bounded size.  `arrow` streams sorted
partitions through a numpy loop and holds one model and one batch in memory; this
is the route for large tables.  `grouped` is the arrow route with a model for
each value of some columns.

A table to be folded has columns k (order key), x array<double> and y double.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import vectors as V
from . import prox as P
from .tasks import LinearTask

STATE = "seg long, n long, steps long, w array<double>, loss_start double, loss_seen double"


def sorted_rows(*cols: str) -> Column:
    """All rows of a group as one array in the order of `cols`; the sort is part of the value, so no plan can drop it."""
    return F.sort_array(F.collect_list(F.struct(*cols)))


def step_column(task: LinearTask, w: Column, x: Column, y: Column, alpha, reg: P.Prox | None = None, share: float = 0.0) -> Column:
    """The model after one row."""
    moved = V.let(task.move(V.dot(w, x), y) * alpha, lambda c: V.axpy(w, c, x))
    return moved if reg is None or reg.name == "none" else V.let(moved, lambda v: reg.column(v, alpha * share))


def fold_catalyst(df: DataFrame, task: LinearTask, start: Column | list[float], alpha: float, keys: list[str] = (), reg: P.Prox | None = None, share: float = 0.0) -> DataFrame:
    """(keys..., n, w): the fold of each group, as one aggregate expression."""
    start = V.literal(start) if isinstance(start, list) else start
    rows = df.groupBy(*keys).agg(sorted_rows("k", "x", "y").alias("rows"))
    w = F.aggregate("rows", start, lambda a, r: step_column(task, a, r["x"], r["y"], alpha, reg, share))
    return rows.select(*keys, F.size("rows").cast("long").alias("n"), w.alias("w"))


def fold_progressive(df: DataFrame, task: LinearTask, start: list[float], alpha: float) -> DataFrame:
    """(n, w, loss_start, loss_progressive): losses from the same pass, at the pass's first model and at each row's current one."""
    w0 = V.literal(start)
    zero = F.struct(w0.alias("w"), F.lit(0.0).alias("a"), F.lit(0.0).alias("b"))

    def step(s: Column, r: Column) -> Column:
        return V.let(
            V.dot(s["w"], r["x"]),
            lambda u: F.struct(V.let(task.move(u, r["y"]) * alpha, lambda c: V.axpy(s["w"], c, r["x"])).alias("w"), (s["a"] + task.loss_of(w0, r["x"], r["y"])).alias("a"), (s["b"] + task.loss(u, r["y"])).alias("b")),
        )

    rows = df.agg(sorted_rows("k", "x", "y").alias("rows"))
    out = rows.select(F.size("rows").cast("long").alias("n"), F.aggregate("rows", zero, step).alias("s"))
    return out.select("n", F.col("s.w").alias("w"), F.col("s.a").alias("loss_start"), F.col("s.b").alias("loss_progressive"))


def dense(column: pa.Array) -> np.ndarray:
    """A list column whose lists have one length, as a matrix without copying."""
    flat = column.flatten()
    return np.asarray(flat).reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def walk(task: LinearTask, w: np.ndarray, x: np.ndarray, y: np.ndarray, alpha: Callable[[int], float] | float, steps: int = 0, reg: P.Prox | None = None, share: float = 0.0, batch: int = 1) -> tuple[np.ndarray, int]:
    """Steps over rows in order, in place; `batch` above 1 averages that many rows into one step, which is another method."""
    fixed, plain = not callable(alpha), reg is None or reg.name == "none"
    if batch == 1:
        one, dot = task.one(), w.dot
        for row, target in zip(x, y.tolist(), strict=True):
            steps += 1
            a = alpha if fixed else alpha(steps)
            c = a * one(float(dot(row)), target)
            if c:
                w += c * row
            if not plain:
                w[:] = reg.array(w, a * share)
        return w, steps
    for at in range(0, len(y), batch):
        steps += 1
        a = alpha if fixed else alpha(steps)
        part, target = x[at : at + batch], y[at : at + batch]
        w += (a / len(target)) * (task.move_np(part @ w, target) @ part)
        if not plain:
            w[:] = reg.array(w, a * share * len(target))
    return w, steps


def fold_arrow(df: DataFrame, task: LinearTask, start: np.ndarray, alpha: Callable[[int], float] | float, reg: P.Prox | None = None, share: float = 0.0, batch: int = 1, state: str = "inplace", presorted: bool = False) -> DataFrame:
    """One row (seg, n, steps, w, loss_start, loss_seen) for each value of `seg` in each partition.

    The table has k, x, y and seg and is partitioned by seg; it is sorted by
    (seg, k) in its partitions here unless it is stored so.  `state='passed'`
    copies the model at every row instead of changing it in place, which is what
    an aggregate without shared state does.
    """
    rows = df.select("seg", "k", "x", "y")
    rows = rows if presorted else rows.sortWithinPartitions("seg", "k")

    def runs(batches):
        for b in batches:
            segs, x, y = np.asarray(b.column(0)), dense(b.column(2)), np.asarray(b.column(3))
            cuts = [0, *(np.flatnonzero(np.diff(segs)) + 1).tolist(), len(segs)]
            for lo, hi in zip(cuts, cuts[1:], strict=False):
                if lo < hi:
                    yield int(segs[lo]), x[lo:hi], y[lo:hi]

    return rows.mapInArrow(_folder(runs, task, start, alpha, reg, share, batch, state), STATE)


def _folder(runs, task, start, alpha, reg, share, batch, state):
    """The task body: runs of rows with one seg in, one state for each seg out."""
    begin = np.array(start, float)

    def run(batches):
        seg, n, steps, w, first, seen = None, 0, 0, None, 0.0, 0.0

        def out():
            return pa.RecordBatch.from_arrays([pa.array([seg], pa.int64()), pa.array([n], pa.int64()), pa.array([steps], pa.int64()), pa.array([w.tolist()], pa.list_(pa.float64())), pa.array([first]), pa.array([seen])], names=["seg", "n", "steps", "w", "loss_start", "loss_seen"])

        for s, xs, ys in runs(batches):
            if s != seg:
                if seg is not None:
                    yield out()
                seg, n, steps, w, first, seen = s, 0, 0, begin.copy(), 0.0, 0.0
            first += float(task.loss_np(xs @ begin, ys).sum())
            if state == "passed":
                for i in range(len(ys)):
                    w = w.copy()
                    w, steps = walk(task, w, xs[i : i + 1], ys[i : i + 1], alpha, steps, reg, share)
            else:
                w, steps = walk(task, w, xs, ys, alpha, steps, reg, share, batch)
            n += len(ys)
        if seg is not None:
            yield out()

    return run


PACKED = "seg long, b int, n int, xs binary, ys binary"


def pack(df: DataFrame, block_bytes: int = 1 << 20) -> DataFrame:
    """(seg, b, n, xs, ys): the rows of a sorted table (seg, x, y) as blocks of raw numbers, in order.

    Made once before many passes: a pass then moves blocks of about `block_bytes`
    between the JVM and Python instead of one array for each row.
    """

    def run(batches):
        number = 0
        for b in batches:
            segs, x, y = np.asarray(b.column(0)), dense(b.column(1)), np.asarray(b.column(2))
            most = max(1, block_bytes // (8 * max(1, x.shape[1])))
            cuts = [0, *(np.flatnonzero(np.diff(segs)) + 1).tolist(), len(segs)]
            edges = [(i, min(i + most, hi)) for lo, hi in zip(cuts, cuts[1:], strict=False) for i in range(lo, hi, most)]
            if not edges:
                continue
            ids = np.arange(number, number + len(edges), dtype=np.int32)
            number += len(edges)
            raw = lambda v: [np.ascontiguousarray(v[i:j], np.float64).tobytes() for i, j in edges]
            yield pa.RecordBatch.from_arrays([pa.array(segs[[i for i, _ in edges]]), pa.array(ids), pa.array(np.array([j - i for i, j in edges], np.int32)), pa.array(raw(x), pa.binary()), pa.array(raw(y), pa.binary())], names=["seg", "b", "n", "xs", "ys"])

    return df.select("seg", "x", "y").mapInArrow(run, PACKED)


def _blocks(batches):
    for b in batches:
        for seg, n, xs, ys in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), b.column(3), b.column(4), strict=True):
            yield seg, np.frombuffer(xs.as_buffer(), np.float64).reshape(n, -1), np.frombuffer(ys.as_buffer(), np.float64)


def fold_packed(blocks: DataFrame, task: LinearTask, start: np.ndarray, alpha, reg: P.Prox | None = None, share: float = 0.0, batch: int = 1, state: str = "inplace") -> DataFrame:
    """As `fold_arrow`, over blocks of `pack`."""
    return blocks.mapInArrow(_folder(_blocks, task, start, alpha, reg, share, batch, state), STATE)


def packed_sums(blocks: DataFrame, task: LinearTask, w: np.ndarray, with_gradient: bool = False) -> tuple[float, np.ndarray]:
    """(loss, gradient) of all rows; one partial sum from each partition, added by the driver in no fixed order."""
    w = np.array(w, float)

    def run(batches):
        loss, g = 0.0, np.zeros(len(w))
        for _, x, y in _blocks(batches):
            u = x @ w
            loss += float(task.loss_np(u, y).sum())
            if with_gradient:
                g -= task.move_np(u, y) @ x
        yield pa.RecordBatch.from_arrays([pa.array([loss]), pa.array([g.tolist()], pa.list_(pa.float64()))], names=["loss", "g"])

    got = blocks.mapInArrow(run, "loss double, g array<double>").collect()
    return sum(r.loss for r in got), sum((np.array(r.g) for r in got), np.zeros(len(w)))


def coordinates(model: DataFrame, keys: list[str] = (), digits: int = 6) -> DataFrame:
    """(keys..., j, w): a model column w as rows, rounded, without negative zeros."""
    return model.select(*keys, F.posexplode("w").alias("j", "v")).select(*keys, "j", (F.round("v", digits) + F.lit(0.0)).alias("w"))
