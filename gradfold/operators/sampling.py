"""Reservoir and hash samples, as declarative plans.

A reservoir's slot at position p is a pure function of the seed and p, so what it
holds at the end is the last arrival of each slot, and what it lets go is the
previous arrival of the slot, or the new row if that is rejected.  No iteration.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hashing as H
from .ranks import ranked


def positions(df: DataFrame, by: list[Column]) -> DataFrame:
    """Adds p, the 1-based place in an order, by sorted ranges of it."""
    return ranked(df, by, "p")[0].withColumn("p", F.col("p") + 1)


def slots(df: DataFrame, m: int, seed) -> DataFrame:
    """Adds slot: p - 1 for the first m rows, then hash(seed, p) mod p; rows with a slot of m or more are rejected."""
    seed = seed if isinstance(seed, Column) else F.lit(seed)
    return df.withColumn("slot", F.when(F.col("p") <= m, F.col("p") - 1).otherwise(H.number(seed, F.col("p")) % F.col("p")))


def reservoir(slotted: DataFrame, m: int, keys: list[str] = ()) -> DataFrame:
    """The rows that the reservoir holds after all positions: the last arrival of each slot."""
    rest = [c for c in slotted.columns if c not in (*keys, "slot")]
    held = slotted.where(F.col("slot") < m).groupBy(*keys, "slot").agg(F.max_by(F.struct(*rest), "p").alias("r"))
    return held.select(*keys, "slot", *(F.col(f"r.{c}").alias(c) for c in rest))


def drops(slotted: DataFrame, m: int, keys: list[str] = ()) -> DataFrame:
    """What leaves the reservoir at each position p > m (column `at`): the slot's previous row, or the arriving one if rejected."""
    rest = [c for c in slotted.columns if c not in (*keys, "slot")]
    previous = F.lag(F.struct(*rest)).over(Window.partitionBy(*keys, "slot").orderBy("p"))
    kept = slotted.where(F.col("slot") < m).select(*keys, F.col("p").alias("at"), previous.alias("r")).where("r is not null")
    rejected = slotted.where(F.col("slot") >= m).select(*keys, F.col("p").alias("at"), F.struct(*rest).alias("r"))
    return kept.union(rejected).select(*keys, "at", *(F.col(f"r.{c}").alias(c) for c in rest))


def bottom_m(df: DataFrame, m: int, seed: int = 42, by: str = "id") -> DataFrame:
    """A uniform sample of m rows without replacement: the m smallest hashes.  Each partition keeps m, and no exchange moves more."""
    key = F.struct(H.order_key(seed, F.col(by)), F.col(by))
    return df.orderBy(key).limit(m)


def bernoulli(df: DataFrame, share: float, seed: int = 42, by: str = "id") -> DataFrame:
    return df.where(H.uniform(seed, F.col(by)) < share)


def stratified(df: DataFrame, shares: dict, stratum: str, seed: int = 42, by: str = "id") -> DataFrame:
    share = F.coalesce(*(F.when(F.col(stratum) == k, F.lit(float(v))) for k, v in shares.items()), F.lit(0.0))
    return df.where(H.uniform(seed, F.col(by)) < share)
