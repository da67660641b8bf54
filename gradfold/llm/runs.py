"""Immutable sorted runs in shared storage, the common part of the persistent indexes.

A run holds the rows of one batch, bucketed and sorted by key, in a folder named
after the batches it covers.  It counts once it is complete, and a run that covers
others hides them: a batch that failed is written again under the same name, and
a merge that was cut short changes nothing.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .shared import folders, remove


class Runs:
    def __init__(self, spark: SparkSession, location: str, schema: str, key: str, buckets: int, fan_in: int):
        self.spark, self.location, self.schema, self.key, self.buckets, self.fan_in = spark, location.rstrip("/"), schema, key, buckets, fan_in

    def spans(self) -> list[tuple[int, int]]:
        """(first batch, last batch) of the runs that count, in order."""
        found = [tuple(map(int, name.split("-"))) for name in folders(self.spark, self.location)]
        return sorted(s for s in found if not any(o != s and o[0] <= s[0] and s[1] <= o[1] for o in found))

    def next_batch(self) -> int:
        return max((hi for _, hi in self.spans()), default=0) + 1

    def _name(self, span: tuple[int, int]) -> str:
        return f"{span[0]:06d}-{span[1]:06d}"

    def table(self, span: tuple[int, int]) -> DataFrame:
        """A run, read so that joins on its key exchange nothing of it."""
        path = f"{self.location}/{self._name(span)}"
        name = "run_" + hashlib.md5(path.encode()).hexdigest()
        self.spark.sql(f"CREATE TABLE IF NOT EXISTS {name} ({self.schema}) USING parquet CLUSTERED BY ({self.key}) SORTED BY ({self.key}) INTO {self.buckets} BUCKETS LOCATION '{path}'")
        return self.spark.table(name)

    def tables(self, before: int | None = None) -> list[DataFrame]:
        """The runs that count, of batches before `before`."""
        return [self.table(s) for s in self.spans() if before is None or s[1] < before]

    def _write(self, rows: DataFrame, span: tuple[int, int]) -> None:
        path = f"{self.location}/{self._name(span)}"
        name = "new_" + hashlib.md5(path.encode()).hexdigest()
        self.spark.sql(f"DROP TABLE IF EXISTS {name}")
        sorted_ = rows.repartition(self.buckets, self.key).sortWithinPartitions(self.key)
        sorted_.write.mode("overwrite").format("parquet").bucketBy(self.buckets, self.key).sortBy(self.key).option("path", path).saveAsTable(name)
        self.spark.sql(f"DROP TABLE {name}")  # the files stay

    def append(self, rows: DataFrame, batch: int) -> None:
        self._write(rows, (batch, batch))

    def compact(self, merge: Callable[[DataFrame], DataFrame], always: bool = False) -> None:
        """Merge all runs into one if there are more than `fan_in`; the old ones go when it is complete."""
        spans = self.spans()
        if len(spans) < 2 or len(spans) <= self.fan_in and not always:
            return
        self._write(merge(self.rows()), (spans[0][0], spans[-1][1]))
        for s in spans:
            remove(self.spark, f"{self.location}/{self._name(s)}")

    def rows(self, before: int | None = None) -> DataFrame | None:
        """All rows of the runs that count, of batches before `before`; None without any.

        Read as plain files: a union of bucketed tables claims their partitioning in
        Spark 4.1, and then loses it when the scans are columnar.
        """
        paths = [f"{self.location}/{self._name(s)}" for s in self.spans() if before is None or s[1] < before]
        return self.spark.read.schema(self.schema).parquet(*paths) if paths else None
