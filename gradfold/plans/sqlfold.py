"""DuckDB text of folds, for oracles: a list of rows reduced by a lambda."""

from __future__ import annotations

from ..functions import hashing as H
from .fixtures import D

ZERO = f"list_resize(CAST([] AS DOUBLE[]), {D + 1}, 0.0::DOUBLE)"
#: The fixed model of loss and prediction queries: coordinate j is (j mod 7 - 3) / 10.
MODEL = f"list_transform(range(0, {D}), lambda j: (j % 7 - 3)::DOUBLE / 10.0::DOUBLE)"


def moved(move: str, alpha: float, d: int = D, reg: str = "{v}", t: float = 0.0) -> str:
    """The reducing lambda: a is the model and one more number, r the row with its target at the end."""
    u = f"list_dot_product(a[1:{d}], r[1:{d}])"
    after = reg.replace("{v}", f"(z[1] + c * z[2])").replace("{t}", f"{t!r}::DOUBLE")
    return f"lambda a, r: list_transform([{alpha!r}::DOUBLE * {move.format(u=u, y=f'r[{d + 1}]')}], lambda c: list_transform(list_zip(a, r), lambda z: {after}))[1]"


def fold(rows: str, move: str, alpha: float, d: int = D, start: str | None = None, by: str = "k", reg: str = "{v}", t: float = 0.0) -> str:
    """An aggregate expression over rows of a subquery with columns k, r."""
    start = start or f"list_resize(CAST([] AS DOUBLE[]), {d + 1}, 0.0::DOUBLE)"
    return f"list_reduce(list(r ORDER BY {by}), {moved(move, alpha, d, reg, t)}, {start})"


def keyed(data: str, key: str, extra: str = "") -> str:
    return f"SELECT {key} AS k, list_append(x, y) AS r{extra} FROM ({data})"


def once(data: str, extra: str = "") -> str:
    """Rows in the order of the hash of seed 42 and id."""
    return keyed(data, H.sql_key("42", "id"), extra)


def coords(source: str, d: int = D, keys: str = "") -> str:
    """(keys, j, w) of a subquery with a list column w."""
    return f"SELECT {keys}j::INT AS j, round(v, 6) + 0.0 AS w FROM (SELECT {keys}unnest(range(0, {d})) AS j, unnest(w[1:{d}]) AS v FROM ({source}))"


def average(parts: str, d: int = D, weight: str = "n") -> str:
    return f"SELECT j::INT AS j, round(sum({weight} * v) / sum({weight}), 6) + 0.0 AS w FROM (SELECT n::DOUBLE AS n, unnest(range(0, {d})) AS j, unnest(w[1:{d}]) AS v FROM ({parts})) GROUP BY j"
