"""Java classes for what must run in Spark's own tasks, compiled by the compiler that Spark generates its code with."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

_CLASSES: dict[tuple[str, str], object] = {}


def compiled(spark: SparkSession, name: str, source: str):
    """The class `name` of `source`, known to the driver and sent to executors like any jar of the session; compiled once a session."""
    at = spark._jsparkSession.sessionUUID(), name
    if at not in _CLASSES:
        compiler = spark._jvm.org.codehaus.janino.SimpleCompiler()
        compiler.cook(source)
        code = compiler.getBytecodes()
        path = os.path.join(tempfile.mkdtemp(prefix="gradfold-"), f"{name}.jar")
        with zipfile.ZipFile(path, "w") as jar:
            for each in code:
                jar.writestr(each.replace(".", "/") + ".class", bytes(code[each]))
        spark.sql(f"ADD JAR '{path}'")
        urls = spark.sparkContext._gateway.new_array(spark._jvm.java.net.URL, 1)
        urls[0] = spark._jvm.java.io.File(path).toURI().toURL()
        spark_own = spark._jvm.java.lang.Thread.currentThread().getContextClassLoader()
        _CLASSES[at] = spark._jvm.java.net.URLClassLoader(urls, spark_own).loadClass(name)
    return _CLASSES[at]


def cogrouped(left: DataFrame, right: DataFrame, key: str, by: tuple[str, str], fold, schema: str) -> DataFrame:
    """The rows that a Java CoGroupFunction makes from both sides' rows of each key, a long, as streams in the orders `by`; a side that is dealt by the key is not exchanged."""
    spark = left.sparkSession
    jvm, gateway = spark._jvm, spark.sparkContext._gateway
    encoder = jvm.org.apache.spark.sql.Encoders

    def rows(kind: T.StructType):
        return encoder.row(spark._jsparkSession.parseDataType(kind.json()))

    def grouped(side: DataFrame):
        return getattr(side.groupBy(key)._jgd, "as")(encoder.LONG(), rows(side.schema))

    def order(name: str):
        columns = gateway.new_array(jvm.org.apache.spark.sql.Column, 1)
        columns[0] = jvm.org.apache.spark.sql.functions.col(name)
        return columns

    out = grouped(left).cogroupSorted(grouped(right), order(by[0]), order(by[1]), fold, rows(T._parse_datatype_string(schema)))
    return DataFrame(out, spark)
