"""Data orders, as an explicit key column k.

An order is never left to the physical order of rows: exchanges and retries do not
keep it.  Shuffles are sorts by a hash of seed, epoch and id.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import hashing as H
from .ranks import ranked


class Order:
    #: does every epoch need its own key?
    each_epoch = False
    #: are rows folded as they stream through their input partition, without a key?
    in_place = False

    def key(self, epoch: int) -> Column:
        raise NotImplementedError

    def apply(self, df: DataFrame, epoch: int = 1) -> DataFrame:
        return df.withColumn("k", self.key(epoch))


@dataclass
class Stored(Order):
    by: str = "id"

    def key(self, epoch):
        return F.lpad(F.col(self.by).cast("string"), 20, "0")


@dataclass
class Clustered(Order):
    """All of one class before the next: the pathological order."""

    label: str = "y"
    tie: str = "id"

    def key(self, epoch):
        return F.struct((-F.col(self.label)).alias("a"), F.col(self.tie).alias("b"))


@dataclass
class Reverse(Order):
    """From the last row of a numeric column to the first."""

    by: str = "id"

    def key(self, epoch):
        return -F.col(self.by)


@dataclass
class Alternating(Order):
    """Forwards in odd epochs, backwards in even ones."""

    by: str = "id"
    each_epoch = True

    def key(self, epoch):
        return F.col(self.by) * (1 if epoch % 2 else -1)


@dataclass
class ShuffleOnce(Order):
    seed: int = 42
    by: str = "id"
    fast: bool = False

    def key(self, epoch):
        return (H.fast if self.fast else H.order_key)(self.seed, F.col(self.by))


@dataclass
class ShuffleAlways(Order):
    seed: int = 42
    by: str = "id"
    fast: bool = False
    each_epoch = True

    def key(self, epoch):
        return (H.fast if self.fast else H.order_key)(self.seed, epoch, F.col(self.by))


@dataclass
class Fixed(Order):
    """Any fixed order given by an expression."""

    expression: Column

    def key(self, epoch):
        return self.expression


@dataclass
class WithReplacement(Order):
    """Step k takes row hash(seed, k) mod N of the stored order; rows repeat and others are left out."""

    seed: int = 42
    by: str = "id"
    each_epoch = True

    def apply(self, df, epoch=1):
        numbered, n = ranked(df, [F.col(self.by)], "row")
        steps = df.sparkSession.range(1, n + 1).select(F.col("id").alias("k"), (H.number(self.seed, F.col("id")) % n).alias("row"))
        return steps.join(numbered, "row").drop("row")


@dataclass
class LocalShuffle(Order):
    """No exchange: rows of an input split are permuted through a buffer of bounded size; splits keep their place."""

    seed: int = 42
    buffer: int = 100_000
    each_epoch = True
    in_place = True

    def apply(self, df, epoch=1):
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        schema = df.schema
        limit, seed = self.buffer, self.seed

        def run(batches):
            rng = np.random.default_rng([seed, epoch, TaskContext.get().partitionId()])
            held, size = [], 0
            for b in batches:
                held.append(b)
                size += b.num_rows
                if size >= limit:
                    whole = pa.Table.from_batches(held)
                    yield from whole.take(pa.array(rng.permutation(whole.num_rows))).combine_chunks().to_batches()
                    held, size = [], 0
            if held:
                whole = pa.Table.from_batches(held)
                yield from whole.take(pa.array(rng.permutation(whole.num_rows))).combine_chunks().to_batches()

        return df.mapInArrow(run, schema)
