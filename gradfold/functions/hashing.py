"""Hashes that give the same value in every SQL engine (md5 of the parts joined by colons).

They define orders, segments and samples that do not depend on partitions, task
retries or an engine's random numbers.  `fast` is for runs that need no such parity.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def order_key(*parts) -> Column:
    return F.md5(F.concat_ws(":", *(_text(p) for p in parts)))


def number(*parts) -> Column:
    """A non-negative long below 2**32."""
    return F.conv(F.substring(order_key(*parts), 1, 8), 16, 10).cast("long")


def uniform(*parts) -> Column:
    return number(*parts) / F.lit(4294967296.0)


def fast(*parts) -> Column:
    return F.xxhash64(*(_text(p) for p in parts))


def _text(p) -> Column:
    return p.cast("string") if isinstance(p, Column) else F.lit(str(p))


# the same in DuckDB


def sql_key(*parts: str) -> str:
    return f"md5(concat_ws(':', {', '.join(parts)}))"


def sql_number(*parts: str) -> str:
    return f"('0x' || substr({sql_key(*parts)}, 1, 8))::BIGINT"
