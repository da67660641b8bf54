"""What the corpus operators have in common: shared storage and Arrow plumbing."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from . import kernels


_LOCAL: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a fresh local one where that is unset and there is one machine only."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        app = spark.sparkContext.applicationId
        found = _LOCAL[app] = _LOCAL.get(app) or tempfile.mkdtemp(prefix="gradfold-")
    return found.rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write a table to shared storage and read it again: it is computed once, and survives lost executors."""
    path = fresh_path(df.sparkSession, label)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def discard(*tables: DataFrame) -> None:
    """Remove tables that `stored` wrote, once nothing will read them again."""
    for df in tables:
        remove(df.sparkSession, df.stored_at)


def _folder(spark: SparkSession, path: str):
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    return where, where.getFileSystem(spark._jsc.hadoopConfiguration())


def remove(spark: SparkSession, path: str) -> None:
    where, system = _folder(spark, path)
    system.delete(where, True)


def folders(spark: SparkSession, path: str) -> list[str]:
    """The names of the complete tables below a folder, in any file system that Spark reads."""
    where, system = _folder(spark, path)
    if not system.exists(where):
        return []
    found = [f.getPath() for f in system.listStatus(where) if f.isDirectory()]
    done = spark._jvm.org.apache.hadoop.fs.Path
    return [p.getName() for p in found if system.exists(done(p, "_SUCCESS"))]


def apart(df: DataFrame) -> DataFrame:
    """A side of a join that grows with the input and so must not be broadcast.

    Spark judges by the size of files: a small file of alike rows may be a table that the driver cannot hold.
    """
    return df.hint("merge")


def release(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files of finished steps now: it does so when the driver collects the objects that own them."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def free_name(df: DataFrame, base: str) -> str:
    """`base`, lengthened until no column of the table has it."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base += "_"
    return base


def quoted(name: str) -> Column:
    return F.col("`" + name.replace("`", "``") + "`")


def append_struct(df: DataFrame, into: str, fields: T.StructType, text: str, work: Callable, keep: list[str] | None = None, limit: int = kernels.SLICE_BYTES) -> DataFrame:
    """All rows and columns of a table, with a struct column that `work` makes from slices of it.

    `work()` is called once in each task and gives a function from a RecordBatch
    with about `limit` bytes of text to a dict of Arrow arrays or lists, one for each field.
    `into` is lengthened by underscores if one of the columns kept has that name.
    """
    keep = df.columns if keep is None else keep
    while into.lower() in {c.lower() for c in keep}:
        into += "_"
    schema = T.StructType([*(f for f in df.schema.fields if f.name in keep), T.StructField(into, fields, False)])
    names = fields.fieldNames()
    kinds = [to_arrow_type(f.dataType) for f in fields]

    def run(batches):
        each = work()
        for batch in batches:
            for part in kernels.slices(batch, text, limit):
                got = each(part)
                made = [got[n] if isinstance(got[n], pa.Array) else pa.array(got[n], k) for n, k in zip(names, kinds, strict=True)]
                struct = pa.StructArray.from_arrays(made, names)
                cols = [part.column(part.schema.get_field_index(c)) for c in keep]
                yield pa.RecordBatch.from_arrays([*cols, struct], names=[*keep, into])

    return df.mapInArrow(run, schema)


def ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
