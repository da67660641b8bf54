"""Low-rank factorisation of observed cells (i, j, m): m ~ L_i . R_j.

The serial fold walks over the cells in order.  For scale the cells are cut into a
grid of P x P blocks by hashed row and column; the P blocks of a diagonal share no
row and no column, so they are folded side by side without conflicts, each with its
own slices of both factors (a cogroup by block), and an epoch is P diagonals.  Cells
are packed and dealt once; what moves between diagonals are factor slices, one
binary row each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions import vectors as V
from ..sources.files import scratch
from .folds import sorted_rows
from .sparse import labels


def start_factor(side: str, ident: Column, rank: int, size: float = 0.5) -> Column:
    """Start values by a hash of side, id and component: equal in every part and every engine."""
    return F.array(*(H.uniform(side, ident, k) * size for k in range(rank)))


def sql_start(side: str, ident: str, rank: int, size: float = 0.5) -> str:
    return "[" + ", ".join(f"{H.sql_number(repr(side), ident, str(k))} / 4294967296.0::DOUBLE * {size}::DOUBLE" for k in range(rank)) + "]"


def initial(cells: DataFrame, rank: int, size: float = 0.5) -> DataFrame:
    """(side, id, f) for every row and column that has a cell."""
    left = cells.select("i").distinct().select(F.lit("L").alias("side"), F.col("i").alias("id"))
    right = cells.select("j").distinct().select(F.lit("R").alias("side"), F.col("j").alias("id"))
    return left.union(right).select("side", "id", F.when(F.col("side") == "L", start_factor("L", F.col("id"), rank, size)).otherwise(start_factor("R", F.col("id"), rank, size)).alias("f"))


def fold_small(cells: DataFrame, rows: int, cols: int, rank: int, alpha: float, mu: float = 0.0, size: float = 0.5) -> DataFrame:
    """(side, id, k, f): one epoch over cells (k, i, j, m) with 0 <= i < rows and 0 <= j < cols, as one aggregate over a flat array.

    For small matrices only: the whole model is rebuilt at every cell.
    """
    flat = [start_factor("L", F.lit(i), rank, size) for i in range(rows)] + [start_factor("R", F.lit(j), rank, size) for j in range(cols)]
    start = F.flatten(F.array(*flat))
    grouped = cells.agg(sorted_rows("k", "i", "j", "m").alias("rows"))

    def step(w: Column, r: Column) -> Column:
        a, b = r["i"] * rank, (F.lit(rows) + r["j"]) * rank
        left, right = F.slice(w, a + 1, rank), F.slice(w, b + 1, rank)
        shrink = 1.0 / (1.0 + 2.0 * alpha * mu)

        def moved(c: Column) -> Column:
            return F.transform(w, lambda v, p: F.when((p >= a) & (p < a + rank), (v + c * F.element_at(w, (b + p - a + 1).cast("int"))) * shrink).when((p >= b) & (p < b + rank), (v + c * F.element_at(w, (a + p - b + 1).cast("int"))) * shrink).otherwise(v))

        return V.let((r["m"] - V.dot(left, right)) * (2.0 * alpha), moved)

    out = grouped.select(F.posexplode(F.aggregate("rows", start, step)).alias("p", "v"))
    base = F.floor(F.col("p") / rank).cast("int")
    return out.select(F.when(base < rows, "L").otherwise("R").alias("side"), F.when(base < rows, base).otherwise(base - rows).alias("id"), (F.col("p") % rank).alias("k"), (F.round("v", 6) + F.lit(0.0)).alias("f"))


def walk_cells(left: np.ndarray, right: np.ndarray, i: np.ndarray, j: np.ndarray, m: np.ndarray, alpha: float, mu: float = 0.0) -> float:
    """Steps over cells in order, in place; the sum of squared errors met on the way."""
    total, shrink = 0.0, 1 / (1 + 2 * alpha * mu)
    for a, b, v in zip(i.tolist(), j.tolist(), m.tolist(), strict=True):
        l, r = left[a], right[b]
        e = v - float(l @ r)
        total += e * e
        old = l.copy()
        l += 2 * alpha * e * r
        r += 2 * alpha * e * old
        if mu:
            l *= shrink
            r *= shrink
    return total


def _block(ident: str, parts: int, side: str) -> Column:
    return F.pmod(F.xxhash64(F.lit(side), F.col(ident)), F.lit(parts)).cast("int")


PACKED = "g long, bi int, bj int, kind int, n int, ids binary, other binary, m binary"


def _packed_cells(cells: DataFrame, parts: int, names: list[int], key: Column) -> DataFrame:
    """(g, bi, bj, kind, n, ids, other, m): the cells of each pair of blocks as raw numbers in order, all pairs of a row block in one partition."""
    label = F.element_at(F.array(*(F.lit(n).cast("long") for n in names)), F.col("bi") + 1)
    rows = cells.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), F.col("m").cast("double").alias("m"), _block("i", parts, "L").alias("bi"), _block("j", parts, "R").alias("bj"), key.alias("k"))
    rows = rows.withColumn("g", label).repartition(parts, "g").sortWithinPartitions("g", "bj", "k", "i", "j").select("g", "bi", "bj", "i", "j", "m")

    def run(batches):
        for b in batches:
            g, bi, bj, i, j, m = (np.asarray(b.column(n)) for n in range(6))
            cut = np.flatnonzero((np.diff(g) != 0) | (np.diff(bj) != 0)) + 1
            edges = [(lo, hi) for lo, hi in zip([0, *cut], [*cut, len(g)], strict=True) if lo < hi]
            raw = lambda v, kind: pa.array([np.ascontiguousarray(v[lo:hi], kind).tobytes() for lo, hi in edges], pa.binary())
            first = np.array([lo for lo, _ in edges], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(g[first]), pa.array(bi[first]), pa.array(bj[first]), pa.array(np.zeros(len(edges), np.int32)), pa.array(np.array([hi - lo for lo, hi in edges], np.int32)), raw(i, np.int64), raw(j, np.int64), raw(m, np.float64)], names=["g", "bi", "bj", "kind", "n", "ids", "other", "m"])

    return rows.mapInArrow(run, PACKED).repartition(parts, "g").sortWithinPartitions("g", "bj")


FACTOR = "side string, b int, ids binary, f binary, loss double"


def _unpacked(ids: bytes, f: bytes) -> tuple[np.ndarray, np.ndarray]:
    own = np.frombuffer(ids, np.int64)
    return own, np.frombuffer(f, np.float64).reshape(len(own), -1) if len(own) else np.zeros((0, 1))


def _diagonal(shift: int, parts: int, alpha: float, mu: float):
    """The fold of a row block's cells with the column block that is its partner now, over both slices of the factors."""

    def work(cells: pa.Table, model: pa.Table) -> pa.Table:
        sides = {s: (b, ids, f) for s, b, ids, f in zip(*(model.column(c).to_pylist() for c in ("side", "b", "ids", "f")), strict=True)}
        total = 0.0
        if "L" in sides and "R" in sides:
            (bl, idl, fl), (br, idr, fr) = sides["L"], sides["R"]
            left_ids, left = _unpacked(idl, fl)
            right_ids, right = _unpacked(idr, fr)
            left, right = left.copy(), right.copy()
            for bj, i, j, m in zip(*(cells.column(c).to_pylist() for c in ("bj", "ids", "other", "m")), strict=True):
                if bj == br:
                    i, j, m = np.frombuffer(i, np.int64), np.frombuffer(j, np.int64), np.frombuffer(m, np.float64)
                    total += walk_cells(left, right, np.searchsorted(left_ids, i), np.searchsorted(right_ids, j), m, alpha, mu)
            sides = {"L": (bl, idl, left.tobytes()), "R": (br, idr, right.tobytes())}
        names = list(sides)
        return pa.table({"side": pa.array(names, pa.string()), "b": pa.array([sides[n][0] for n in names], pa.int32()), "ids": pa.array([sides[n][1] for n in names], pa.binary()), "f": pa.array([sides[n][2] for n in names], pa.binary()), "loss": pa.array([total if not k else 0.0 for k in range(len(names))], pa.float64())})

    return work


def fit_strata(cells: DataFrame, rank: int, epochs: int, alpha, parts: int = 4, mu: float = 0.0, seed: int = 42, size: float = 0.5, store=None, key: Column | None = None) -> tuple[DataFrame, list[float]]:
    """(side, id, f) and the squared error met in each epoch, over cells (i, j, m) with integer i and j.

    The cells are packed once and stay where they are; a diagonal exchanges one
    binary row for each factor slice, and its loss comes with them.  `store(df)`
    writes those after each diagonal and reads them again (default: the shared
    folder), which keeps lineage short.  `key` orders the cells of a block (a hash
    without one).
    """
    spark = cells.sparkSession
    cells = cells.withColumns({"i": F.col("i").cast("long"), "j": F.col("j").cast("long")})
    names = labels(spark, parts)
    held = _packed_cells(cells, parts, names, H.fast(seed, F.col("i"), F.col("j")) if key is None else key).persist()

    def kept(df: DataFrame) -> DataFrame:
        path = scratch(spark, "factors")
        df.write.parquet(path)
        return spark.read.schema(FACTOR).parquet(path)

    store = store or kept
    start = initial(cells, rank, size).select("side", F.col("id").cast("long").alias("id"), "f")
    start = start.withColumn("b", F.when(F.col("side") == "L", F.pmod(F.xxhash64(F.lit("L"), "id"), F.lit(parts))).otherwise(F.pmod(F.xxhash64(F.lit("R"), "id"), F.lit(parts))).cast("int"))

    def slices(part: pa.Table) -> pa.Table:
        order = np.argsort(part.column("id").to_numpy(), kind="stable")
        f = np.asarray(part.column("f").combine_chunks().flatten(), np.float64).reshape(part.num_rows, -1)[order]
        ids = part.column("id").to_numpy()[order].astype(np.int64)
        return pa.table({"side": pa.array([part.column("side")[0].as_py()]), "b": pa.array([part.column("b")[0].as_py()], pa.int32()), "ids": pa.array([ids.tobytes()], pa.binary()), "f": pa.array([f.tobytes()], pa.binary()), "loss": pa.array([0.0])})

    factors = store(start.groupBy("side", "b").applyInArrow(slices, FACTOR))
    losses = []
    for e in range(1, epochs + 1):
        a, loss = alpha(e), 0.0
        for s in range(parts):
            row_block = F.when(F.col("side") == "L", F.col("b")).otherwise(F.pmod(F.col("b") - s, F.lit(parts)))
            lined = factors.select(F.element_at(F.array(*(F.lit(n).cast("long") for n in names)), row_block + 1).alias("g"), "side", "b", "ids", "f")
            factors = store(held.groupBy("g").cogroup(lined.groupBy("g")).applyInArrow(_diagonal(s, parts, a, mu), FACTOR))
            loss += factors.agg(F.sum("loss")).first()[0] or 0.0
        losses.append(loss)
    held.unpersist()

    def rows(batches):
        for b in batches:
            for side, ids, f in zip(*(b.column(c).to_pylist() for c in ("side", "ids", "f")), strict=True):
                own, w = _unpacked(ids, f)
                yield pa.RecordBatch.from_arrays([pa.array([side] * len(own)), pa.array(own), pa.array(w.tolist(), pa.list_(pa.float64()))], names=["side", "id", "f"])

    return factors.select("side", "ids", "f").mapInArrow(rows, "side string, id long, f array<double>"), losses


def predict(cells: DataFrame, factors: DataFrame) -> DataFrame:
    """Adds prediction to cells (i, j, ...): two joins by id and a dot product."""
    left = factors.where("side = 'L'").select(F.col("id").alias("i"), F.col("f").alias("fl"))
    right = factors.where("side = 'R'").select(F.col("id").alias("j"), F.col("f").alias("fr"))
    return cells.join(left, "i").join(right, "j").withColumn("prediction", V.dot(F.col("fl"), F.col("fr"))).drop("fl", "fr")


def loss(cells: DataFrame, factors: DataFrame, mu: float = 0.0) -> DataFrame:
    """(n, loss): squared error over the cells plus the penalty on both factors."""
    fit = predict(cells, factors).agg(F.count("*").alias("n"), F.sum((F.col("m") - F.col("prediction")) ** 2).alias("fit"))
    weight = factors.agg(F.sum(V.dot(F.col("f"), F.col("f"))).alias("weight"))
    return fit.crossJoin(F.broadcast(weight)).select("n", F.round(F.col("fit") + mu * F.col("weight"), 6).alias("loss"))
