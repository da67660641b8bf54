"""Two tasks on series: smoothing of a hidden state, and portfolios on the simplex."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .prox import onto_simplex


def smooth_walk(w: np.ndarray, t: np.ndarray, y: np.ndarray, alpha: float, c: np.ndarray, a: np.ndarray, w0: np.ndarray | None) -> np.ndarray:
    """Steps over observations (t from 1, y): each touches the states of t and t - 1 only.  w has one row for each t."""
    for i in range(len(t)):
        k = int(t[i]) - 1
        before = w[k - 1] if k else (w0 if w0 is not None else None)
        now = w[k].copy()
        fit = c @ now - y[i]
        drift = now - a @ before if before is not None else np.zeros_like(now)
        w[k] = now - alpha * 2 * (c.T @ fit + drift)
        if k and before is not None:
            w[k - 1] = before + alpha * 2 * (a.T @ drift)
    return w


def smooth_exact(y: np.ndarray, c: np.ndarray | None = None, a: np.ndarray | None = None, w0: np.ndarray | None = None) -> np.ndarray:
    """The minimiser, by a forward and a backward sweep over the chain's blocks; w0 None leaves the state before the first free.

    Work and memory are in the length of the series.
    """
    n, s = len(y), (y.shape[1] if c is None else c.shape[1])
    c = np.eye(s) if c is None else c
    a = np.eye(s) if a is None else a
    if not n:
        return np.zeros((0, s))
    own, tie, following = c.T @ c, np.eye(s), a.T @ a
    lead, right = np.empty((n, s, s)), np.empty((n, s))
    for t in range(n):
        d = own + (tie if t or w0 is not None else 0) + (following if t + 1 < n else 0)
        r = c.T @ y[t] + (a @ w0 if not t and w0 is not None else 0)
        if t:
            # the block left of the diagonal is -a
            d = d - a @ lead[t - 1]
            r = r + a @ right[t - 1]
        lead[t], right[t] = np.linalg.solve(d, a.T), np.linalg.solve(d, r)
    for t in range(n - 2, -1, -1):
        right[t] += lead[t] @ right[t + 1]
    return right


def smoothing_loss(df: DataFrame, w0: float = 0.0) -> DataFrame:
    """(n, loss) of a scalar series (t, y, w): squared fit and squared drift."""
    before = F.coalesce(F.lag("w").over(Window.orderBy("t")), F.lit(w0))
    each = df.select(((F.col("w") - F.col("y")) ** 2 + (F.col("w") - before) ** 2).alias("l"))
    return each.agg(F.count("*").alias("n"), F.round(F.sum("l"), 6).alias("loss"))


def covariance(returns: DataFrame) -> DataFrame:
    """(a, b, cov) of long returns (t, a, r): population covariance of every pair, as a join on time."""
    other = returns.select("t", F.col("a").alias("b"), F.col("r").alias("s"))
    return returns.join(other, "t").where("a <= b").groupBy("a", "b").agg(F.round(F.covar_pop("r", "s") * 1e6, 6).alias("cov"))


def portfolio_walk(w: np.ndarray, r: np.ndarray, alpha: float, mean: np.ndarray, passes: int = 1) -> np.ndarray:
    """Projected steps over periods (rows of returns); the objective is -mean.w + w'Cov w, separable over periods."""
    n = len(r)
    for _ in range(passes):
        for row in r:
            c = row - mean
            w = onto_simplex(w - alpha * (-mean / n + 2 * float(c @ w) * c / n))
    return w


def portfolio_objective(w: np.ndarray, r: np.ndarray) -> float:
    mean = r.mean(axis=0)
    return float(-mean @ w + np.mean(((r - mean) @ w) ** 2))


def portfolio_exact(r: np.ndarray) -> np.ndarray:
    """The minimiser for few assets: the best stationary point over all supports."""
    n, mean = r.shape[1], r.mean(axis=0)
    cov = (r - mean).T @ (r - mean) / len(r)
    best, found = np.inf, np.full(n, 1 / n)
    for mask in range(1, 1 << n):
        s = [i for i in range(n) if mask >> i & 1]
        k = np.zeros((len(s) + 1, len(s) + 1))
        k[:-1, :-1] = 2 * cov[np.ix_(s, s)]
        k[:-1, -1] = k[-1, :-1] = 1
        x = np.linalg.lstsq(k, np.append(mean[s], 1.0), rcond=None)[0][:-1]
        if (x >= -1e-12).all():
            w = np.zeros(n)
            w[s] = np.maximum(x, 0)
            w /= w.sum()
            if (v := portfolio_objective(w, r)) < best:
                best, found = v, w
    return found


def fit_smoothing(rows: DataFrame, epochs: int, alpha, every: int = 1) -> DataFrame:
    """(series, epoch, loss) of scalar series (series, t, y) with t from 1: each is folded on an executor, its states beside it."""
    steps = [alpha(e) for e in range(1, epochs + 1)]

    def work(own: pa.Table) -> pa.Table:
        own = own.sort_by("t")
        y, t = own.column("y").to_numpy()[:, None], np.arange(1, own.num_rows + 1)
        w, out = np.zeros_like(y), []
        for e, step in enumerate(steps, 1):
            smooth_walk(w, t, y, step, np.eye(1), np.eye(1), np.zeros(1))
            if e % every == 0:
                before = np.vstack([[[0.0]], w[:-1]])
                out.append((e, float(((w - y) ** 2).sum() + ((w - before) ** 2).sum())))
        name = own.column("series")[0].as_py()
        return pa.table({"series": pa.array([name] * len(out), own.schema.field("series").type), "epoch": pa.array([o[0] for o in out], pa.int32()), "loss": pa.array([o[1] for o in out], pa.float64())})

    return rows.select("series", "t", "y").groupBy("series").applyInArrow(work, f"series {rows.schema['series'].dataType.simpleString()}, epoch int, loss double")


def fit_portfolio(periods: DataFrame, assets: int, epochs: int, alpha) -> np.ndarray:
    """Weights from rows (k, r) of returns, r an array of `assets`: projected steps in the order of k, one job a pass, the model between passes with the driver."""
    stats = periods.agg(F.count("*"), *(F.avg(F.col("r")[i]) for i in range(assets))).first()
    n, mean = stats[0], np.array(stats[1:], float)
    held = periods.select("k", "r").repartition(1).sortWithinPartitions("k").persist()
    w = np.full(assets, 1 / assets)
    for e in range(1, epochs + 1):
        begin, step = w, alpha(e)

        def run(batches, begin=begin, step=step):
            w = begin
            for b in batches:
                for row in np.asarray(b.column(1).flatten()).reshape(-1, assets):
                    c = row - mean
                    w = onto_simplex(w - step * (-mean / n + 2 * float(c @ w) * c / n))
            yield pa.RecordBatch.from_arrays([pa.array([w.tolist()], pa.list_(pa.float64()))], names=["w"])

        got = held.mapInArrow(run, "w array<double>").collect()  # one model
        w = np.array(got[0].w) if got else w
    held.unpersist()
    return w
