"""Multiplexed reservoir sampling: learning from data too large to shuffle.

While a pass reads the rows, one worker keeps a reservoir of m of them and steps on
each row that the reservoir lets go; another steps on the reservoir of the pass
before, on the same model.  After a pass the new reservoir takes the old one's place.

`schedule` is the deterministic form: which row is the nth step does not depend on
the model, so all epochs are one table, and any fold runs it.  `fit_partitioned`
is the form for scale: every partition streams its rows once per epoch with its own
buffers of m / P rows, no row is exchanged, and models are averaged per epoch.
"""

from __future__ import annotations

import threading

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import sampling as S
from .folds import dense, walk
from .tasks import LinearTask


def schedule(df: DataFrame, order: list[Column], m: int, epochs: int, mem_steps: int = 1, seed: int = 42, io_target: str = "dropped") -> DataFrame:
    """(epoch, p, sub, worker, id, x, y): all steps; fold them in the order of (epoch, p, sub).

    At position p the io worker steps (sub 0) on the row let go there
    (`io_target='arriving'`: on the row just read), then the memory worker takes
    `mem_steps` steps through the last reservoir, round and round.
    """
    cols = ["id", "x", "y"]
    placed = S.positions(df.select(*cols), order)
    every = placed.crossJoin(F.broadcast(df.sparkSession.range(1, epochs + 1).select(F.col("id").cast("int").alias("epoch"))))
    slotted = S.slots(every, m, F.lit(seed) + F.col("epoch"))
    if io_target == "dropped":
        io = S.drops(slotted.select("epoch", "p", "slot", *cols), m, ["epoch"]).select("epoch", F.col("at").alias("p"), F.lit(0).alias("sub"), F.lit("io").alias("worker"), *cols)
    elif io_target == "arriving":
        io = every.select("epoch", "p", F.lit(0).alias("sub"), F.lit("io").alias("worker"), *cols)
    else:
        raise ValueError(io_target)
    if mem_steps == 0 or m == 0:
        return io
    buffer = S.reservoir(slotted.select("epoch", "p", "slot", *cols), m, ["epoch"]).select((F.col("epoch") + 1).alias("epoch"), "slot", *cols)
    ticks = every.where("epoch > 1").select("epoch", "p", F.explode(F.sequence(F.lit(1), F.lit(mem_steps))).alias("sub"))
    filled = F.least(F.lit(m), F.lit(df.count())).cast("long")
    ticks = ticks.withColumn("slot", ((F.col("p") - 1) * mem_steps + F.col("sub") - 1) % filled)
    mem = ticks.join(buffer, ["epoch", "slot"]).select("epoch", "p", "sub", F.lit("memory").alias("worker"), *cols)
    return io.union(mem)


#: Bytes of buffered rows that are carried from one pass to the next at most.
CARRIED = 256 << 20


def fit_partitioned(df: DataFrame, task: LinearTask, d: int, m: int, epochs: int, alpha, mem_steps: int = 1, seed: int = 42, threaded: bool = False, start=None, period: int = 10, swap: str = "period") -> tuple[np.ndarray, list[dict]]:
    """(model, history) over a table (x, y) as it is partitioned; one job an epoch, its input is not moved.

    Each task has two buffers of m / partitions rows.  swap='pass': the reservoir of
    a pass is what the memory worker steps on in the next one; the m rows travel
    with the model, and a bound on their bytes is checked.  swap='period', a variant:
    the buffers change places whenever `period` times that many rows have been read,
    so nothing but the model outlives a task.  Either way a task that is lost runs
    again from the epoch's first model.  The models are averaged by rows.  `threaded`
    lets the memory worker run beside the scan instead of in turns.
    """
    if swap not in ("pass", "period"):
        raise ValueError(swap)
    if swap == "pass" and 8 * m * (d + 1) > CARRIED:
        raise ValueError("the buffers are too large to be carried between passes; swap='period' carries none")
    w = np.zeros(d) if start is None else np.array(start, float)
    size = max(1, m // max(1, df.rdd.getNumPartitions()))
    rows, history, carried = df.select("x", "y"), [], {}
    whole = swap == "pass"
    for e in range(1, epochs + 1):
        shared = df.sparkSession.sparkContext.broadcast(carried)

        def run(batches, begin=w, a=alpha(e), e=e, shared=shared):
            part = TaskContext.get().partitionId()
            rng = np.random.default_rng([seed, e, part])
            model, loss, n, p, j = begin.copy(), 0.0, 0, 0, 0
            one, step_dot = task.one(), model.dot

            def step(row, target):
                c = a * one(float(step_dot(row)), float(target))
                if c:
                    model.__iadd__(c * row)

            fill_x, fill_y = np.zeros((size, len(begin))), np.zeros(size)
            use: tuple[np.ndarray, np.ndarray] | None = shared.value.get(part)
            stop = threading.Event()

            def memory():
                at, mine = 0, None
                while not stop.is_set():
                    if use is not mine:
                        at, mine = 0, use
                    if mine is None:
                        stop.wait(0.001)
                        continue
                    step(mine[0][at], mine[1][at])
                    at = (at + 1) % len(mine[1])

            thread = threading.Thread(target=memory, daemon=True) if threaded else None
            if thread:
                thread.start()
            try:
                for b in batches:
                    x, y = dense(b.column(0)), np.asarray(b.column(1))
                    loss += float(task.loss_np(x @ begin, y).sum())
                    for i in range(len(y)):
                        n, p = n + 1, p + 1
                        s = p - 1 if p <= size else int(rng.integers(p))
                        if p > size:
                            step(*((fill_x[s], fill_y[s]) if s < size else (x[i], y[i])))
                        if s < size:
                            fill_x[s], fill_y[s] = x[i], y[i]
                        if use is not None and not thread:
                            for _ in range(mem_steps):
                                step(use[0][j], use[1][j])
                                j = (j + 1) % len(use[1])
                        if not whole and p == period * size:
                            use, p, j = (fill_x.copy(), fill_y.copy()), 0, 0
                left = min(p, size)
                if not whole:  # what the buffer still holds has not been used
                    walk(task, model, fill_x[:left], fill_y[:left], a)
            finally:
                stop.set()
                if thread:
                    thread.join()
            if n:
                kept = left if whole else 0
                arrays = [pa.array([part], pa.int32()), pa.array([n], pa.int64()), pa.array([loss]), *(pa.array([v.tolist()], pa.list_(pa.float64())) for v in (model, fill_x[:kept].ravel(), fill_y[:kept]))]
                yield pa.RecordBatch.from_arrays(arrays, names=["part", "n", "loss", "w", "xs", "ys"])

        got = rows.mapInArrow(run, "part int, n long, loss double, w array<double>, xs array<double>, ys array<double>").collect()  # a model and a buffer from each partition
        shared.unpersist()
        total = sum(r.n for r in got)
        w = sum(r.n * np.array(r.w) for r in got) / total if total else w
        carried = {r.part: (np.array(r.xs).reshape(-1, d), np.array(r.ys)) for r in got if r.ys}
        history.append({"epoch": e, "loss_start": sum(r.loss for r in got), "rows": total, "buffered": sum(len(v[1]) for v in carried.values())})
    return w, history
