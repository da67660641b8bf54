"""Quality classifier by co-training.

Two views of a document are classified separately: its text (shares of byte
values, of transitions between character classes, and measures of repetition) and
its metadata (language, source, length).  In each round both views score all
documents in one pass without a shuffle; of those that a view is sure about, anew
by a hash in every round, it hands some with its own label to the other view's
training set.  At the end each view is calibrated on labelled documents that
neither was trained on, and a logistic combination of both gives the score.

Models are fitted by the driver, on a bounded sample of labelled documents and a
bounded number of pseudo-labels a round, which are drawn from all documents.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels
from .shared import append_struct, free_name, quoted

#: Labelled documents that are used (about; by a hash of the id).
LABELLED = 6000
#: Rounds, the probability from which a view is sure, and documents that each view hands over in a round.
ROUNDS, SURE, HANDED = 3, 0.97, 400
CUT = 0.5
#: Features are made of less text at a time: a byte of it takes about 100 bytes of arrays, in each of an executor's workers.
PART_BYTES = 1 << 18

_CLASS = np.zeros(256, np.int64)
for _c, _bytes in enumerate([b"\n\r", b" \t", bytes(range(0x30, 0x3A)), bytes(range(0x41, 0x5B)), bytes(range(0x61, 0x7B)), b".,;:'\"?-()", bytes(range(0x80, 0x100))], 1):
    _CLASS[list(_bytes)] = _c
_KINDS = 8
_BYTES = 129  # ASCII values, and all others as one


def text_features(column: pa.Array) -> np.ndarray:
    """(texts, features) of the content view; null and empty texts have zeros and a one."""
    data, offs = kernels.text_bytes(column)
    n, sizes = len(offs) - 1, np.diff(offs)
    doc = np.repeat(np.arange(n), sizes)
    per = np.maximum(sizes, 1)[:, None]
    shares = np.bincount(doc * _BYTES + np.minimum(data, 128), minlength=n * _BYTES).reshape(n, _BYTES) / per
    kind = _CLASS[data]
    same = doc[1:] == doc[:-1]
    moves = np.bincount((doc[1:] * _KINDS + kind[:-1])[same] * _KINDS + kind[1:][same], minlength=n * _KINDS**2).reshape(n, -1) / per
    words = kernels.spaced_words(data, offs)
    hashes, counts = words.hashes(), words.counts
    owner = np.repeat(np.arange(n), counts)
    some = np.maximum(counts, 1)
    again = np.zeros(n)
    if len(hashes) > 1:
        beside = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
        again = np.bincount(owner[1:][beside], minlength=n) / some
    order = np.lexsort((hashes, owner))
    h, o = hashes[order], owner[order]
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
    distinct = np.bincount(o[fresh], minlength=n) / some
    length = np.bincount(owner, (words.ends - words.starts), minlength=n) / some
    return np.column_stack([np.sqrt(shares), np.sqrt(moves), again, distinct, np.log1p(length), np.log1p(counts), distinct * np.log1p(counts), sizes == 0])


def _hashed(values: list, size: int) -> np.ndarray:
    out = np.zeros((len(values), size))
    codes, names = pd.factorize(np.array([str(v) for v in values], object))
    spots = pd.util.hash_array(np.array(names, object), categorize=False) % size if len(names) else np.zeros(0, np.int64)
    out[np.arange(len(values)), spots[codes].astype(int) if len(values) else []] = 1
    return out


def meta_features(part: pa.RecordBatch, columns: list[str], text: str) -> np.ndarray:
    """(rows, features) of the metadata view: hashed categories, logarithms of numbers, and the text's length."""
    made = []
    for c in columns:
        col = part.column(part.schema.get_field_index(c))
        if pa.types.is_integer(col.type) or pa.types.is_floating(col.type):
            v = np.nan_to_num(np.array(col.to_pylist(), float))
            made += [np.sign(v) * np.log1p(np.abs(v)), np.array(col.is_null())]
        else:
            made.append(_hashed(col.to_pylist(), 64))
    sizes = np.diff(kernels.text_bytes(part.column(part.schema.get_field_index(text)))[1])
    return np.column_stack([*made, np.log1p(sizes)])


@dataclass
class Linear:
    mean: np.ndarray
    spread: np.ndarray
    weights: np.ndarray

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.spread, -8, 8) @ self.weights[:-1] + self.weights[-1]


def fit(x: np.ndarray, y: np.ndarray, penalty: float = 1.0, steps: int = 25) -> Linear:
    """Logistic regression by Newton steps with a squared penalty; rows are a bounded sample."""
    mean, spread = x.mean(axis=0), x.std(axis=0)
    spread[spread < 1e-9] = 1e9
    z = np.column_stack([np.clip((x - mean) / spread, -8, 8), np.ones(len(x))])
    w = np.zeros(z.shape[1])
    ridge = np.full(len(w), penalty)
    ridge[-1] = 1e-6
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        g = z.T @ (p - y) + ridge * w
        move = np.linalg.solve((z * (p * (1 - p) + 1e-6)[:, None]).T @ z + np.diag(ridge), g)
        size = np.abs(move).max()
        w -= move * min(1, 5 / size) if size else 0
        if size < 1e-6:
            break
    return Linear(mean, spread, w)


@dataclass
class CoTrained:
    text: Linear | None
    meta: Linear | None
    both: Linear | None
    base: float
    columns: list[str]
    rounds: list[dict]

    def scores(self, t: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Probabilities of quality by text, by metadata and by both."""
        if self.text is None:
            return tuple(np.full(len(t), self.base) for _ in range(3))
        a, b = self.text.logit(t), self.meta.logit(m)
        c = self.both.logit(np.column_stack([a, b]))
        return tuple(1 / (1 + np.exp(-np.clip(v, -30, 30))) for v in (a, b, c))


def chances(model: Linear, x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(model.logit(x), -30, 30)))


def co_train(t: np.ndarray, m: np.ndarray, y: np.ndarray, sure_of: Callable[[int, list[Linear]], list[tuple[np.ndarray, np.ndarray]]], columns: list[str], rounds: int = ROUNDS) -> CoTrained:
    """Fit on labelled (t, m, y) documents and on what the views label for each other.

    `sure_of(round, models)` gives for each view the features, in the other view, and
    the labels of documents that it hands over.  With one class only, or fewer than
    20 documents, every score is the labels' mean.
    """
    base = float(y.mean()) if len(y) else 1.0
    if len(y) < 20 or min(y.sum(), len(y) - y.sum()) < 5:
        return CoTrained(None, None, None, base, columns, [])
    third = np.arange(len(y)) % 3 == 0  # kept for calibration
    views = [t, m]
    train = [(v[~third], y[~third]) for v in views]
    log = []
    for r in range(rounds):
        given = sure_of(r, [fit(*d) for d in train])
        for i, (x, labels) in enumerate(given):
            if len(labels):
                train[1 - i] = (np.concatenate([train[1 - i][0], x]), np.concatenate([train[1 - i][1], labels]))
        log.append({"round": r, "by_text": len(given[0][1]), "by_meta": len(given[1][1])})
        if not any(len(labels) for _, labels in given):
            break
    models = [fit(*d) for d in train]
    held = np.column_stack([model.logit(v[third]) for model, v in zip(models, views, strict=True)])
    return CoTrained(models[0], models[1], fit(held, y[third]), base, columns, log)


def _features(part: pa.RecordBatch, text: str, columns: list[str]) -> tuple[np.ndarray, np.ndarray]:
    return text_features(part.column(part.schema.get_field_index(text))), meta_features(part, columns, text)


def _parts(batch: pa.RecordBatch, text: str, columns: list[str]):
    """(slice, its features in both views) for the slices of a batch, in memory for one slice."""
    for part in kernels.slices(batch, text, PART_BYTES):
        yield part, _features(part, text, columns)


def _spot(ident: str, of: str) -> Column:
    """A number in [0, 1) by a hash of the id."""
    return F.xxhash64(quoted(ident).cast("string"), F.lit(of)).bitwiseAND(F.lit((1 << 40) - 1).cast("long")) / float(1 << 40)


HANDED_OVER = "view int, spot double, i string, y double, x array<double>"


def handed_over(docs: DataFrame, models: list[Linear], taken: set[str], number: int, ident: str, text: str, columns: list[str], sure: float = SURE, handed: int = HANDED) -> list[tuple[list[str], np.ndarray, np.ndarray]]:
    """For each view the ids, the other view's features and the labels of `handed` documents, of all that it is sure about those with the least hashes.

    One pass over all documents; a task remembers and gives `handed` rows for each view at most.
    """
    shared = docs.sparkSession.sparkContext.broadcast((models, taken))
    some = docs.where(quoted(ident).isNotNull()).select(quoted(ident).cast("string").alias("__i"), _spot(ident, f"round {number}").alias("__s"), quoted(text).alias("__t"), *(quoted(c).alias(f"__m{n}") for n, c in enumerate(columns)))
    names = [f"__m{n}" for n in range(len(columns))]

    def run(batches):
        views, gone = shared.value
        best: list[list[tuple]] = [[], []]  # (spot, id, label, features in the other view)
        for batch in batches:
            for part, feats in _parts(batch, "__t", names):
                ids, spots = part.column(0).to_pylist(), np.asarray(part.column(1))
                for i, model in enumerate(views):
                    p = chances(model, feats[i])
                    sure_ones = np.flatnonzero(np.maximum(p, 1 - p) >= sure)
                    if len(best[i]) >= handed:
                        sure_ones = sure_ones[spots[sure_ones] <= best[i][-1][0]]
                    new = [(float(spots[n]), ids[n], float(p[n] > 0.5), feats[1 - i][n]) for n in sure_ones.tolist() if ids[n] not in gone]
                    best[i] = sorted([*best[i], *new], key=lambda v: v[:2])[:handed]
        rows = [(i, *v) for i in (0, 1) for v in best[i]]
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.string()), pa.array([r[3] for r in rows], pa.float64()), pa.array([r[4].tolist() for r in rows], pa.list_(pa.float64()))], names=["view", "spot", "i", "y", "x"])

    found = some.mapInArrow(run, HANDED_OVER).persist()
    out = []
    for i in (0, 1):
        rows = found.where(F.col("view") == i).orderBy("spot", "i").limit(handed).collect()
        out.append(([r.i for r in rows], np.array([r.x for r in rows], float), np.array([r.y for r in rows], float)))
    found.unpersist()
    return out


def train(docs: DataFrame, labels: DataFrame, ident: str = "doc_id", text: str = "text", label: str = "quality", columns: tuple[str, ...] = ("lang", "source", "n_chars"), labelled: int = LABELLED, rounds: int = ROUNDS) -> CoTrained:
    """Fit on about `labelled` labelled documents of `docs`, chosen by a hash of their ids, and on pseudo-labels from all others.

    Rows without id or label are no examples; several labels of one id count by their mean.
    """
    columns = [c for c in columns if c in docs.columns]
    known = labels.where(quoted(ident).isNotNull() & quoted(label).isNotNull())
    n_labels = known.count()
    mine = known.where(_spot(ident, "quality sample") < min(1.0, labelled / max(1, n_labels))).groupBy(quoted(ident).alias("__i")).agg(F.avg(quoted(label).cast("double")).alias("__y"))
    # about `labelled` rows are broadcast, whatever the size of the tables
    chosen = docs.select(quoted(ident), quoted(text), *map(quoted, columns)).join(F.broadcast(mine), quoted(ident) == F.col("__i"))
    fields = T.StructType([T.StructField("t", T.ArrayType(T.DoubleType())), T.StructField("m", T.ArrayType(T.DoubleType()))])

    def work():
        def each(part):
            t, m = _features(part, text, columns)
            return {"t": t.tolist(), "m": m.tolist()}

        return each

    rows = append_struct(chosen, "__f", fields, text, work, keep=[ident, "__y"], limit=PART_BYTES).toPandas()
    rows = rows.sort_values(ident, kind="stable").reset_index(drop=True)
    t, m = (np.array([f[k] for f in rows["__f"]], float) if len(rows) else np.zeros((0, 1)) for k in ("t", "m"))
    taken = {str(i) for i in rows[ident]}

    def sure_of(number, models):
        got = handed_over(docs, models, taken, number, ident, text, columns)
        taken.update(i for ids, _, _ in got for i in ids)
        return [(x, y) for _, x, y in got]

    return co_train(t, m, (rows["__y"].to_numpy(float) >= 0.5).astype(float), sure_of, columns, rounds)


SCORED = T.StructType([T.StructField(n, T.DoubleType(), False) for n in ("text_score", "meta_score", "score")] + [T.StructField("accepted", T.BooleanType(), False)])


def score(docs: DataFrame, model: CoTrained, text: str = "text", into: str = "quality", cut: float = CUT, keep: list[str] | None = None) -> DataFrame:
    """All rows and columns with a struct of each view's probability, the combined score, and whether it reaches `cut`.

    Null and empty texts are scored like others; null metadata is a category of its own.
    """
    into = free_name(docs, into)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def work():
        fitted = shared.value

        def each(part):
            t, m = _features(part, text, fitted.columns)
            a, b, c = fitted.scores(t, m)
            return {"text_score": a, "meta_score": b, "score": c, "accepted": c >= cut}

        return each

    def arrays():
        each = work()
        return lambda part: {k: pa.array(v) for k, v in each(part).items()}

    return append_struct(docs, into, SCORED, text, arrays, keep, PART_BYTES)
