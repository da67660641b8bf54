"""Sharding along a Hilbert curve over metadata.

Each dimension is quantised into buckets of equal depth, a row's buckets are its
cell, and rows are sorted by the cell's place on the curve: rows that are near in
all dimensions stand near each other, so a filter on any of them prunes most
shards.  The sorted order is cut into runs of equal row counts.

The place in the global order comes from one range exchange of ids and metadata:
each sorted partition is stored with its rows' places in it, and the partitions'
sizes (one number each) give where each of them begins.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import free_name, partitions, quoted, stored

BITS = 8


def hilbert_index(cells: np.ndarray, bits: int) -> np.ndarray:
    """Places on the Hilbert curve of integer points (rows of `cells`, `bits` bits each); after Skilling, 2004."""
    x = [c.astype(np.int64) for c in cells.T]
    n = len(x)
    if n == 1:
        return x[0]
    q = 1 << bits - 1
    while q > 1:
        for i in range(n):
            high = (x[i] & q) != 0
            swap = np.where(high, 0, (x[0] ^ x[i]) & (q - 1))
            x[0] = np.where(high, x[0] ^ (q - 1), x[0] ^ swap)
            if i:
                x[i] = x[i] ^ swap
        q >>= 1
    for i in range(1, n):
        x[i] = x[i] ^ x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << bits - 1
    while q > 1:
        t = np.where((x[-1] & q) != 0, t ^ (q - 1), t)
        q >>= 1
    x = [v ^ t for v in x]
    out = np.zeros_like(t)
    for b in range(bits - 1, -1, -1):
        for v in x:
            out = out << 1 | v >> b & 1
    return out


def _depths(df: DataFrame, name: str, bits: int) -> DataFrame:
    """(value, cell) for each distinct value of a column that is no number: by the share of rows before it in the order of whole values.

    Values are counted before they are exchanged; sorted ranges of them and the rows
    in each range (one number each) give the rows before a value.
    """
    spark = df.sparkSession
    counts = df.where(F.col(name).isNotNull()).groupBy(F.col(name).alias("value")).agg(F.count("*").alias("n"))
    runs = counts.repartitionByRange(partitions(spark), "value").withColumn("run", F.spark_partition_id())
    runs = stored(runs, "value-runs")
    begin, total = _begins(runs.groupBy("run").agg(F.sum("n")).collect())  # one row for each range
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("run").orderBy("value").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    middle = _begin_of(begin, F.col("run")) + inside + F.floor(F.col("n") / 2)
    # cell 0 is for nulls
    return stored(runs.select("value", F.least(F.lit(1) + F.floor(middle * ((1 << bits) - 1) / F.lit(max(total, 1))), F.lit((1 << bits) - 1)).alias("cell")), "value-cells")


def _begins(sizes: list) -> tuple[dict[int, int], int]:
    begin, total = {}, 0
    for p, n in sorted(sizes):
        begin[p], total = total, total + n
    return begin, total


def _begin_of(begin: dict[int, int], part: Column) -> Column:
    return F.element_at(F.create_map(*(F.lit(x) for p, b in begin.items() for x in (p, b))), part).cast("long") if begin else F.lit(0).cast("long")


def with_curve(df: DataFrame, dims: list[str], into: str, bits: int = BITS) -> DataFrame:
    """All rows and columns with the Hilbert place of each row over `dims`; nulls are the first cell of their dimension.

    Numbers and times are cut at their quantiles, other values by their places among
    whole values.
    """
    simple = (T.NumericType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)
    numeric = [d for d in dims if isinstance(df.schema[d].dataType, simple)]
    number = lambda d: (quoted(d).cast("timestamp") if isinstance(df.schema[d].dataType, (T.DateType, T.TimestampNTZType)) else quoted(d)).cast("double")
    probs = [i / ((1 << bits) - 1) for i in range(1, (1 << bits) - 1)]
    cut = df.agg(*(F.percentile_approx(number(d), probs, 10_000).alias(f"c{i}") for i, d in enumerate(numeric))).first() if numeric else []
    cuts = {d: np.unique(np.array(c, float)) if c else np.zeros(0) for d, c in zip(numeric, cut, strict=True)}  # below 2**bits numbers each
    out, cells = df, []
    for n, d in enumerate(dims):
        if d in cuts:
            cells.append(number(d))
            continue
        v, c = free_name(out, f"value{n}"), free_name(out, f"cell{n}")
        of = _depths(df.select(quoted(d).alias("d")), "d", bits).select(F.col("value").alias(v), F.col("cell").cast("double").alias(c))
        out = out.join(of, quoted(d) == F.col(v), "left").drop(v)
        cells.append(F.col(c))
    sorted_cuts = [cuts.get(d) for d in dims]

    @F.pandas_udf("long")
    def place(*cols: pd.Series) -> pd.Series:
        known = [(s.to_numpy(float), c) for s, c in zip(cols, sorted_cuts, strict=True)]
        points = [np.where(np.isnan(v), 0, v if c is None else 1 + np.searchsorted(c, v, "right")) for v, c in known]
        return pd.Series(hilbert_index(np.stack(points, axis=1).astype(np.int64), bits))

    return out.withColumn(into, place(*cells)).select(*df.columns, into)


def ranked(df: DataFrame, order: list[str], into: str = "rank") -> tuple[DataFrame, int]:
    """The rows with their place (from 0) in the total order, and their number."""
    spark = df.sparkSession
    part, at = free_name(df, "part"), free_name(df, "at")
    runs = df.repartitionByRange(partitions(spark), *map(quoted, order)).sortWithinPartitions(*map(quoted, order))
    runs = stored(runs.withColumn(part, F.spark_partition_id()).withColumn(at, F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1).cast("long"))), "sorted-runs")
    begin, total = _begins(runs.groupBy(part).count().collect())  # one row for each partition
    return runs.select(*map(quoted, df.columns), (_begin_of(begin, F.col(part)) + F.col(at)).alias(into)), total


def shards(docs: DataFrame, dims: list[str], count: int = 16, ident: str = "doc_id", text: str = "text", bits: int = BITS) -> DataFrame:
    """(ident, size, text_crc32, law, shard, slot, grown_shard): which of `count` shards each row goes to, and where.

    The law is `rows`: shards differ by at most one row.  size is the text's bytes
    in UTF-8 plus one; a null text has none and the checksum of no bytes.  Equal
    cells are ordered by checksum and size, so equal texts of one cell stand
    together, then by id.  Null ids come first; an empty table gives no rows.
    """
    raw = F.encode(F.coalesce(quoted(text), F.lit("")), "utf-8")
    base = docs.select(quoted(ident).alias("i"), (F.octet_length(raw) + 1).cast("long").alias("size"), F.crc32(raw).alias("crc"), *(quoted(d).alias(f"d{n}") for n, d in enumerate(dims)))
    base = stored(base, "shard-metadata")
    placed = with_curve(base, [f"d{n}" for n in range(len(dims))], "h", bits)
    rows, total = ranked(placed.select("i", "size", "crc", "h"), ["h", "crc", "size", "i"])
    total = max(total, 1)
    first = F.expr(f"(shard * {total} + {count - 1}) div {count}")
    out = rows.withColumn("shard", F.expr(f"cast(rank * {count} div {total} as int)"))
    return out.select(F.col("i").alias(ident), "size", F.col("crc").alias("text_crc32"), F.lit("rows").alias("law"), "shard", (F.col("rank") - first).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def write_shards(docs: DataFrame, path: str, dims: list[str], count: int = 16, ident: str = "doc_id", text: str = "text", bits: int = BITS) -> str:
    """Write the whole rows as one folder for each of `count` shards, in curve order; the name of the column that has the shard.

    The rows themselves are placed, so ids may be null or repeat, and every row is
    written once.  The order is that of `shards`; the shard's column is named `shard`,
    lengthened if the table has that name.  Null texts are kept as they are, and an
    empty table writes no folder.
    """
    h, size, crc, rank, shard = (free_name(docs, x) for x in ("curve", "text_size", "text_crc", "place", "shard"))
    raw = F.encode(F.coalesce(quoted(text), F.lit("")), "utf-8")
    keyed = with_curve(docs, dims, h, bits).withColumns({size: F.octet_length(raw), crc: F.crc32(raw)})
    rows, total = ranked(keyed, [h, crc, size, ident], rank)
    out = rows.withColumn(shard, F.expr(f"cast(`{rank}` * {count} div {max(total, 1)} as int)"))
    out = out.repartitionByRange(count * 4, shard, rank).sortWithinPartitions(shard, rank)
    out.select(*map(quoted, docs.columns), quoted(shard)).write.partitionBy(shard).parquet(path)
    return shard
