"""Linear-chain conditional random fields over sequences of (features, tag).

A sequence's score is the sum over positions of the weights of its active
features for its tags plus the transition weights; the loss is the negative log
probability of the tags.  Expectations come from forward and backward recursions
in the log domain, and only features that are active in a sequence are touched.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.files import scratch
from . import chain_fold, sparse

SEQUENCE = "seq_id string, feats array<array<int>>, tags array<int>"


def _lse(a: np.ndarray, axis: int) -> np.ndarray:
    top = a.max(axis=axis, keepdims=True)
    return (top + np.log(np.exp(a - top).sum(axis=axis, keepdims=True))).squeeze(axis)


@lru_cache
def _recursion(tags: int, back: bool):
    """A function from the factors by position and the moves to the scaled vectors and their scales, written out for this number of tags.

    Plain numbers are several times as fast as arrays of a few tags.  Backwards,
    positions come from the last one, and a vector does not hold its own factor.
    """
    k = range(tags)
    each = lambda form, sep=", ": sep.join(form.format(j=j) for j in k)
    if back:
        first, here = each("1.0"), [each("g{j} = x{j} * v{j}", "; "), *(f"n{i} = " + " + ".join(f"m{i}_{j} * g{j}" for j in k) for i in k)]
    else:
        first, here = each("x{j}"), [f"n{j} = (" + " + ".join(f"v{i} * m{i}_{j}" for i in k) + f") * x{j}" for j in k]
    moves = ", ".join(f"m{i}_{j}" for i in k for j in k)
    lines = [
        f"def run(each, {moves}):",
        f" {each('x{j}')}, = each[0]",
        f" {each('v{j}')}, = {first},",
        f" total = {each('v{j}', ' + ')}",
        " if not total > 0: return None, None",
        f" {'; '.join(f'v{j} /= total' for j in k)}",
        f" out, scales = [({each('v{j}')},)], [total]",
        f" for {each('x{j}')}, in each[{':-1' if back else '1:'}]:",
        *(f"  {line}" for line in here),
        f"  total = {each('n{j}', ' + ')}",
        "  if not total > 0: return None, None",
        f"  {'; '.join(f'v{j} = n{j} / total' for j in k)}",
        f"  out.append(({each('v{j}')},))",
        "  scales.append(total)",
        " return out, scales",
    ]
    made: dict = {}
    exec("\n".join(lines), made)  # noqa: S102
    return made["run"]


@dataclass
class Chain:
    emit: np.ndarray  # (features, tags)
    move: np.ndarray  # (tags, tags)

    @classmethod
    def zero(cls, features: int, tags: int) -> Chain:
        return cls(np.zeros((features, tags)), np.zeros((tags, tags)))

    def potentials(self, feats: list) -> np.ndarray:
        return np.stack([self.emit[np.asarray(f, np.int64)].sum(axis=0) for f in feats])

    def forward(self, pot: np.ndarray) -> np.ndarray:
        out = np.empty_like(pot)
        out[0] = pot[0]
        for t in range(1, len(pot)):
            out[t] = _lse(out[t - 1][:, None] + self.move, 0) + pot[t]
        return out

    def backward(self, pot: np.ndarray) -> np.ndarray:
        out = np.zeros_like(pot)
        for t in range(len(pot) - 2, -1, -1):
            out[t] = _lse(self.move + (pot[t + 1] + out[t + 1])[None, :], 1)
        return out

    def score(self, pot: np.ndarray, tags) -> float:
        tags = np.asarray(tags)
        return float(pot[np.arange(len(tags)), tags].sum() + self.move[tags[:-1], tags[1:]].sum())

    def loss(self, feats: list, tags) -> float:
        pot = self.potentials(feats)
        return float(_lse(self.forward(pot)[-1], 0)) - self.score(pot, tags)

    def _scaled(self, pot: np.ndarray):
        """As `marginals`, by products of numbers scaled at each position; None if they leave the range of floats."""
        top, lift = pot.max(axis=1), self.move.max()
        e, m = np.exp(pot - top[:, None]), np.exp(self.move - lift)
        ahead, scales = _recursion(len(m), False)(e.tolist(), *m.ravel().tolist())
        behind, _ = _recursion(len(m), True)(e[::-1].tolist(), *m.ravel().tolist())
        if ahead is None or behind is None:
            return None
        f, b = np.array(ahead), np.array(behind[::-1])
        single = f * b
        total = single.sum(axis=1, keepdims=True)
        g = e[1:] * b[1:]
        between = ((f[:-1] @ m) * g).sum(axis=1, keepdims=True)
        if not (total.all() and between.all()):
            return None
        pair = m * ((f[:-1] / between).T @ g)
        return single / total, pair, float(np.log(scales).sum() + top.sum() + (len(pot) - 1) * lift)

    def marginals(self, pot: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """(position marginals, summed pair marginals, log partition)."""
        if (scaled := self._scaled(pot)) is not None:
            return scaled
        f, b = self.forward(pot), self.backward(pot)
        z = float(_lse(f[-1], 0))
        single = np.exp(f + b - z)
        pair = np.zeros_like(self.move)
        for t in range(1, len(pot)):
            pair += np.exp(f[t - 1][:, None] + self.move + (pot[t] + b[t])[None, :] - z)
        return single, pair, z

    def _slope(self, pot: np.ndarray, tags) -> tuple[np.ndarray, np.ndarray, float]:
        single, pair, z = self.marginals(pot)
        tags = np.asarray(tags)
        emit = -single
        emit[np.arange(len(tags)), tags] += 1
        move = -pair
        np.add.at(move, (tags[:-1], tags[1:]), 1)
        return emit, move, z - self.score(pot, tags)

    def gradient(self, feats: list, tags) -> tuple[list, np.ndarray, np.ndarray, float]:
        """Ascent direction: (features by position, emission part by position, transition part) and the loss."""
        return feats, *self._slope(self.potentials(feats), tags)

    def step(self, feats: list, tags, alpha: float, mu: float = 0.0) -> float:
        """One incremental step; the loss before it."""
        sizes = [len(f) for f in feats]
        return self.step_flat(np.fromiter((i for f in feats for i in f), np.int64, sum(sizes)), np.repeat(np.arange(len(feats)), sizes), tags, alpha, mu)

    def step_flat(self, feats: np.ndarray, at: np.ndarray, tags, alpha: float, mu: float = 0.0) -> float:
        """As `step`, from the features of all positions in one array, and the position of each."""
        kinds = self.emit.shape[1]
        pot = np.column_stack([np.bincount(at, w, len(tags)) for w in self.emit[feats].T])
        emit, move, loss = self._slope(pot, tags)
        np.add.at(self.emit.reshape(-1), (feats[:, None] * kinds + np.arange(kinds)).ravel(), (alpha * emit)[at].ravel())
        self.move += alpha * move
        if mu:
            for w in (self.emit, self.move):
                w[:] = np.sign(w) * np.maximum(np.abs(w) - alpha * mu, 0)
        return loss

    def decode(self, feats: list) -> list[int]:
        """The likeliest tags, by a max-product recursion."""
        pot = self.potentials(feats)
        best, back = pot[0], []
        for t in range(1, len(pot)):
            all_ = best[:, None] + self.move
            back.append(all_.argmax(axis=0))
            best = all_.max(axis=0) + pot[t]
        tags = [int(best.argmax())]
        for b in reversed(back):
            tags.append(int(b[tags[-1]]))
        return tags[::-1]


def _sequences(batches: Iterable[pa.RecordBatch]):
    for b in batches:
        yield from zip(*(b.column(i).to_pylist() for i in range(b.num_columns)), strict=True)


def epoch(seqs: DataFrame, model: Chain, alpha: float, mu: float = 0.0) -> list:
    """Fold the partitions of (k, feats, tags), each in the order of k, from one model; a row (n, loss, emit, move) for each.

    The model is one dense array here and travels with the closure.
    """

    def run(batches):
        own = Chain(model.emit.copy(), model.move.copy())
        n, loss = 0, 0.0
        for _, feats, tags in _sequences(batches):
            loss += own.step(feats, tags, alpha, mu)
            n += 1
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([loss]), pa.array([own.emit.ravel().tolist()], pa.list_(pa.float64())), pa.array([own.move.ravel().tolist()], pa.list_(pa.float64()))], names=["n", "loss", "emit", "move"])

    return seqs.select("k", "feats", "tags").sortWithinPartitions("k").mapInArrow(run, "n long, loss double, emit array<double>, move array<double>").collect()


def fit(seqs: DataFrame, features: int, tags: int, epochs: int, alpha, mu: float = 0.0, parts: int = 1) -> tuple[Chain, list[float]]:
    """Incremental training over (k, feats, tags) in `parts` segments with model averaging; the progressive loss of each epoch."""
    model, losses = Chain.zero(features, tags), []
    rows = (seqs.repartition(1) if parts == 1 else seqs.repartition(parts, "k")).persist()
    for e in range(1, epochs + 1):
        got = epoch(rows, model, alpha(e), mu)
        total = sum(r.n for r in got)
        model = Chain(sum(r.n * np.array(r.emit) for r in got).reshape(features, tags) / total, sum(r.n * np.array(r.move) for r in got).reshape(tags, tags) / total)
        losses.append(sum(r.loss for r in got))
    rows.unpersist()
    return model, losses


def _ends(lists: pa.Array) -> np.ndarray:
    """Where each list begins among all their values, and where the last one ends."""
    return np.append(0, np.cumsum(np.asarray(lists.value_lengths()).astype(np.int64)))


def _raw(numbers: pa.Array, cuts: np.ndarray) -> pa.Array:
    """Binary values of little-endian integers, cut at `cuts`; one width, of 1, 2 or 4 bytes, for all."""
    flat = np.asarray(numbers)
    least, most = (int(flat.min()), int(flat.max())) if len(flat) else (0, 0)
    data = np.ascontiguousarray(flat.astype("<i4" if least < 0 or most >= 1 << 16 else "<u2" if most >= 1 << 8 else "u1"))
    return pa.Array.from_buffers(pa.binary(), len(cuts) - 1, [None, pa.py_buffer((data.itemsize * cuts).astype(np.int32)), pa.py_buffer(data)])


def _numbers(batches: Iterable[pa.RecordBatch]):
    """(k, n, sizes, feats, tags) of (k, feats, tags): the positions, and as raw numbers the features of each, all features and the tags."""
    for b in batches:
        feats, tags = b.column(1), b.column(2)
        inner, cuts = feats.flatten(), _ends(feats)
        cols = [_raw(inner.value_lengths(), cuts), _raw(inner.flatten(), _ends(inner)[cuts]), _raw(tags.flatten(), _ends(tags))]
        yield pa.RecordBatch.from_arrays([b.column(0), feats.value_lengths(), *cols], names=["k", "n", "sizes", "feats", "tags"])


def _segment(seg) -> Column:
    """A segment's number as a column that has no nulls on both sides: Spark groups two tables together only by columns of one kind."""
    return F.coalesce(seg, F.lit(-1).cast("long")).alias("seg")


def dealt(seqs: DataFrame, parts: int) -> DataFrame:
    """(seg, k, n, sizes, feats, tags): the sequences as raw numbers, sorted by k inside `parts` segments, each a partition of its own."""
    names = sparse.labels(seqs.sparkSession, parts)
    at = F.pmod(F.xxhash64("k"), F.lit(parts)).cast("int") + 1 if parts > 1 else F.lit(1)
    kind = seqs.schema["k"].dataType.simpleString()
    rows = seqs.select("k", "feats", "tags").mapInArrow(_numbers, f"k {kind}, n int, sizes binary, feats binary, tags binary")
    seg = F.element_at(F.array(*(F.lit(n).cast("long") for n in names)), at)
    rows = rows.select(_segment(seg), "*")
    return rows.repartition(parts, "seg").sortWithinPartitions("seg", "k")


def fit_table(seqs: DataFrame, tags: int, epochs: int, alpha, mu: float = 0.0, parts: int = 1) -> tuple[DataFrame, list[float]]:
    """As `fit`, with the model as a table (feature, w), for any number of features; the progressive loss of each epoch.

    The weight of feature f for tag t is at f * tags + t, that of the move from tag a
    to b at -1 - (a * tags + b).  A segment begins from nothing; after its first epoch
    it gets the weights of the features that it met by a join and gives them back.
    Those must fit a task, its sequences pass by one after the other.  The steps are
    those of `Chain.step_flat`, in Spark's tasks (`chain_fold.py`).
    """
    spark = seqs.sparkSession
    held = dealt(seqs, parts).persist(StorageLevel.MEMORY_AND_DISK)
    weights = spark.createDataFrame([], "seg long, feature long, w double")
    model, history = spark.createDataFrame([], "feature long, w double"), []
    for e in range(1, epochs + 1):
        path = scratch(spark, "chain-epoch")
        chain_fold.folded(held, weights.select(_segment("seg"), "feature", "w").repartition(parts, "seg"), tags, alpha(e), mu).write.parquet(path)
        out = spark.read.schema(chain_fold.OUT).parquet(path)
        model, _, loss = sparse.merged(out.drop("seg"), model)
        weights = out.select("seg", "feature").join(model, "feature").select("seg", "feature", "w")
        history.append(loss)
    held.unpersist()
    return model, history


def batch_step(seqs: DataFrame, model: Chain, alpha: float) -> tuple[Chain, float]:
    """One full-gradient step, the baseline: expectations of all sequences are summed in the tasks first."""

    def run(batches):
        emit, move = np.zeros_like(model.emit), np.zeros_like(model.move)
        n, loss = 0, 0.0
        for feats, tags in _sequences(batches):
            f, e, m, v = model.gradient(feats, tags)
            for one, g in zip(f, e, strict=True):
                np.add.at(emit, np.asarray(one, np.int64), g)
            move += m
            n, loss = n + 1, loss + v
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([loss]), pa.array([emit.ravel().tolist()], pa.list_(pa.float64())), pa.array([move.ravel().tolist()], pa.list_(pa.float64()))], names=["n", "loss", "emit", "move"])

    got = seqs.select("feats", "tags").mapInArrow(run, "n long, loss double, emit array<double>, move array<double>").collect()
    n = max(1, sum(r.n for r in got))
    emit = sum(np.array(r.emit) for r in got).reshape(model.emit.shape)
    move = sum(np.array(r.move) for r in got).reshape(model.move.shape)
    return Chain(model.emit + alpha * emit / n, model.move + alpha * move / n), sum(r.loss for r in got)


def losses(seqs: DataFrame, model: Chain) -> DataFrame:
    """(seq_id, loss) of every sequence."""

    def run(batches):
        for b in batches:
            rows = list(_sequences([b]))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([model.loss(r[1], r[2]) for r in rows], pa.float64())], names=["seq_id", "loss"])

    return seqs.select("seq_id", "feats", "tags").mapInArrow(run, "seq_id string, loss double")


def decoded(seqs: DataFrame, model: Chain) -> DataFrame:
    """(seq_id, tags, predicted)."""

    def run(batches):
        for b in batches:
            rows = list(_sequences([b]))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[2] for r in rows], pa.list_(pa.int32())), pa.array([model.decode(r[1]) for r in rows], pa.list_(pa.int32()))], names=["seq_id", "tags", "predicted"])

    return seqs.select("seq_id", "feats", "tags").mapInArrow(run, "seq_id string, tags array<int>, predicted array<int>")
