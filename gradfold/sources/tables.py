"""Tables of a data folder, and schema checks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def require(df: DataFrame, **kinds: str) -> DataFrame:
    """Fail before a job starts if a column is missing or of another type."""
    have = {f.name: f.dataType.simpleString() for f in df.schema.fields}
    wrong = {c: (k, have.get(c)) for c, k in kinds.items() if have.get(c) != k}
    if wrong:
        raise TypeError("columns (wanted, found): " + ", ".join(f"{c} {w}" for c, w in wrong.items()))
    return df


def training_schema(id_type: T.DataType | None = None) -> T.StructType:
    return T.StructType([T.StructField("id", id_type or T.LongType()), T.StructField("x", T.ArrayType(T.DoubleType())), T.StructField("y", T.DoubleType())])
