"""Places of rows in a total order, without one task that sees them all."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.files import scratch

_LOW = (1 << 33) - 1


def sorted_runs(df: DataFrame, order: list[Column], part: str, at: str) -> tuple[DataFrame, dict[int, int]]:
    """The rows with their run and their place in it, and the rows of each run.

    Runs are ranges of the order.  They are written to the shared folder, so that
    their sizes and their rows come from one and the same exchange.
    """
    spark = df.sparkSession
    runs = df.repartitionByRange(*order).sortWithinPartitions(*order)
    runs = runs.withColumns({part: F.spark_partition_id(), at: F.monotonically_increasing_id().bitwiseAND(F.lit(_LOW).cast("long"))})
    path = scratch(spark, "sorted-runs")
    runs.write.parquet(path)
    runs = spark.read.schema(runs.schema).parquet(path)
    return runs, dict(sorted(runs.groupBy(part).count().collect()))  # one row for each run


def offsets(sizes: dict[int, float], part: str) -> Column:
    """What all earlier runs hold together, by run."""
    begin, total = [], 0
    for p, n in sizes.items():
        begin += [F.lit(p), F.lit(total)]
        total += n
    return F.element_at(F.create_map(*begin), F.col(part)) if begin else F.lit(0)


def ranked(df: DataFrame, order: list[Column], into: str) -> tuple[DataFrame, int]:
    """The rows with their place from 0 in the total order as a long column, and their number.

    Ties are placed in no set order; end `order` with a unique column.
    """
    runs, sizes = sorted_runs(df, order, "__run", "__at")
    rank = offsets(sizes, "__run").cast("long") + F.col("__at")
    return runs.select(*df.columns, rank.alias(into)), sum(sizes.values())
