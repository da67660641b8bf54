"""Parallel schemes: model averaging, and concurrent updates of one model in shared memory.

`shared_epoch` runs them for real inside a host: Python workers of one job attach to
one shared segment and write to it under a lock, under a lock for each block of
components, or without.  `stale_schedule` and `simulate` are the deterministic
counterpart: which model version each step sees is a function of the step number.
"""

from __future__ import annotations

import contextlib
import fcntl
import os
import threading
import uuid
from concurrent.futures import ThreadPoolExecutor
from multiprocessing import resource_tracker, shared_memory

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .folds import _blocks, dense
from .tasks import LinearTask

SCHEMES = ("lock", "aig", "nolock")


def simulate(task: LinearTask, x: np.ndarray, y: np.ndarray, alpha: float, scheme: str = "lock", workers: int = 4, seed: int = 42, epochs: int = 1, start: np.ndarray | None = None) -> np.ndarray:
    """Bounded-staleness simulation of `workers` concurrent writers over rows in order.

    Rows are dealt to the workers in rounds.  Step g sees the model of step g - tau,
    where tau is 1 under a lock and else the number of workers.  Component-wise
    writes are all kept (`aig`).  Without locks a write is lost if a later worker of
    the round writes the component too and the two overlap, which a hash of step,
    component and seed says of one in 97.
    """
    if scheme not in SCHEMES:
        raise ValueError(scheme)
    tau = 1 if scheme == "lock" else workers
    w = np.zeros(x.shape[1]) if start is None else np.array(start, float)
    past = [w.copy()]
    g = 0
    #: For each row, whether a later worker of its round has the component.
    covered = np.zeros(x.shape, bool)
    if scheme == "nolock" and workers > 1:
        for i in range(len(y) - 2, -1, -1):
            if i % workers != workers - 1:
                covered[i] = covered[i + 1] | (x[i + 1] != 0)
    for _ in range(epochs):
        for i in range(len(y)):
            seen = past[max(0, len(past) - tau)]
            move = alpha * float(task.move_np(x[i] @ seen, y[i])) * x[i]
            if scheme == "nolock" and workers > 1:
                lost = covered[i] & ((np.arange(len(w)) * 2654435761 + g * 40503 + seed) % 97 == 0)
                move = np.where(lost, 0.0, move)
            w = w + move
            past = [*past[-tau:], w]
            g += 1
    return w


class SharedModel:
    """A model in a memory segment that the workers of a host attach to by name."""

    def __init__(self, d: int, name: str | None = None, start: np.ndarray | None = None):
        self.d, self.owner = d, name is None
        self.name = name or f"gf{uuid.uuid4().hex[:12]}"
        self.block = shared_memory.SharedMemory(self.name, create=self.owner, size=8 * d)
        if not self.owner:  # the creator frees it, not the process that merely attached
            resource_tracker.unregister(self.block._name, "shared_memory")
        self.w = np.ndarray((d,), np.float64, self.block.buf)
        if self.owner:
            self.w[:] = 0 if start is None else start

    def close(self) -> None:
        self.w = None
        self.block.close()
        if self.owner:
            self.block.unlink()


def shared_epoch(df: DataFrame, task: LinearTask, model: SharedModel, alpha: float, scheme: str = "nolock", blocks: int = 8) -> int:
    """One pass of all partitions of (seg, x, y) over one shared model; the number of steps.

    All writers must run on the host that holds the segment, so this is for one
    host or for the hosts' parts of a hybrid run.  Steps have side effects: task
    retries and speculation must be off, and a failed epoch starts again from its
    stored first model.
    """
    name, d = model.name, model.d

    def run(batches):
        from pyspark import TaskContext

        if TaskContext.get().attemptNumber() > 0:
            raise RuntimeError("a shared-memory epoch cannot be retried by task")
        shared = SharedModel(d, name)
        locks = [open(f"/tmp/{name}.{i}.lock", "w") for i in range(1 if scheme == "lock" else blocks if scheme == "aig" else 0)]  # locks between processes of this host only
        edges = np.linspace(0, d, blocks + 1).astype(int)
        steps = 0
        w, move = shared.w, task.move_np
        for b in batches:
            x, y = dense(b.column(0)), np.asarray(b.column(1))
            for i in range(len(y)):
                row = x[i]
                if scheme == "lock":
                    fcntl.flock(locks[0], fcntl.LOCK_EX)
                    w += (alpha * float(move(row @ w, y[i]))) * row
                    fcntl.flock(locks[0], fcntl.LOCK_UN)
                else:
                    delta = (alpha * float(move(row @ w, y[i]))) * row
                    if scheme == "aig":
                        for k in range(blocks):
                            fcntl.flock(locks[k], fcntl.LOCK_EX)
                            w[edges[k] : edges[k + 1]] += delta[edges[k] : edges[k + 1]]
                            fcntl.flock(locks[k], fcntl.LOCK_UN)
                    else:
                        w += delta
                steps += 1
        w = None
        shared.close()
        for f in locks:
            f.close()
        yield pa.RecordBatch.from_arrays([pa.array([steps], pa.int64())], names=["steps"])

    total = sum(r.steps for r in df.select("x", "y").mapInArrow(run, "steps long").collect())
    for i in range(blocks):
        if os.path.exists(f"/tmp/{name}.{i}.lock"):
            os.unlink(f"/tmp/{name}.{i}.lock")
    return total


def hybrid_epoch(blocks: DataFrame, task: LinearTask, start: np.ndarray, alpha: float, threads: int = 4, scheme: str = "nolock") -> DataFrame:
    """(seg, n, w): concurrent writers inside a part, to be averaged between parts (`merge.average`).

    `blocks` are packed rows (`folds.pack`) with a part for each host.  The rows of
    a block are dealt to threads that step on one model of the task, under one lock
    or without; a task that is lost runs again from `start`.
    """
    begin = np.array(start, float)

    def run(batches):
        lock = threading.Lock() if scheme == "lock" else contextlib.nullcontext()
        one = task.one()
        seg, n, w = None, 0, begin.copy()

        def work(x, y):
            for row, target in zip(x, y.tolist(), strict=True):
                with lock:
                    w.__iadd__((alpha * one(float(row @ w), target)) * row)

        def out():
            return pa.RecordBatch.from_arrays([pa.array([seg], pa.int64()), pa.array([n], pa.int64()), pa.array([w.tolist()], pa.list_(pa.float64()))], names=["seg", "n", "w"])

        with ThreadPoolExecutor(threads) as pool:
            for s, x, y in _blocks(batches):
                if s != seg:
                    if seg is not None:
                        yield out()
                    seg, n = s, 0
                    w[:] = begin
                list(pool.map(work, [x[i::threads] for i in range(threads)], [y[i::threads] for i in range(threads)]))
                n += len(y)
        if seg is not None:
            yield out()

    return blocks.mapInArrow(run, "seg long, n long, w array<double>")
