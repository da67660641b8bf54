"""Merging the models of parts (shared-nothing parallel training)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def average(parts: DataFrame, weighting: str = "rows") -> DataFrame:
    """(j, w): the mean of models (n, w) of parts, weighted by their rows or uniform; partial sums before the exchange."""
    weight = F.col("n").cast("double") if weighting == "rows" else F.lit(1.0)
    each = parts.select(weight.alias("weight"), F.posexplode("w").alias("j", "v"))
    return each.groupBy("j").agg((F.sum(F.col("weight") * F.col("v")) / F.sum("weight")).alias("w"))


def average_touched(deltas: DataFrame, parts: int, touched: bool = False) -> DataFrame:
    """(feature, delta) from sparse model changes (seg, feature, delta, n) of `parts` parts.

    Over all parts by default, so that a feature absent from a part counts as
    unchanged there, which equals the dense average; `touched` averages over the
    parts that changed it only.
    """
    n = F.count("*") if touched else F.lit(parts)
    return deltas.groupBy("feature").agg((F.sum("delta") / n).alias("delta"))
