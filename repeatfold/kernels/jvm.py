"""The kernels on the executors' JVM: ``java/Kernel.java`` is built by the compiler that Spark itself brings, once an application, and sent to the
executors as a jar of the session. Units stay in the JVM, so no worker holds a batch of them as Python objects.
"""

from __future__ import annotations

import os
import tempfile
import zipfile
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, StringType, StructType, _parse_datatype_string

SOURCE = os.path.join(os.path.dirname(os.path.abspath(__file__)), "java", "Kernel.java")


def _array(sc, kind, values):
    out = sc._gateway.new_array(kind, len(values))
    for k, v in enumerate(values):
        out[k] = v
    return out


def _loader(spark: SparkSession):
    """The class loader of the compiled classes; their jar is sent once."""
    sc = spark.sparkContext
    if getattr(sc, "_repeatfold_loader", None) is None:
        compiler = sc._jvm.org.codehaus.janino.SimpleCompiler()
        with open(SOURCE) as f:
            compiler.cook(f.read())
        classes = compiler.getBytecodes()
        path = os.path.join(tempfile.mkdtemp(), "repeatfold-kernels.jar")
        with zipfile.ZipFile(path, "w") as z:
            for name in list(classes):
                z.writestr(name.replace(".", "/") + ".class", bytes(classes[name]))
        sc._jsc.addJar(path)
        sc._repeatfold_loader = compiler.getClassLoader()
    return sc._repeatfold_loader


def _made(spark: SparkSession, name: str, *args):
    """An instance of a compiled class; it has one constructor."""
    sc = spark.sparkContext
    return _loader(spark).loadClass(name).getDeclaredConstructors()[0].newInstance(_array(sc, sc._jvm.java.lang.Object, args))


def _kernel(spark: SparkSession):
    sc = spark.sparkContext
    if getattr(sc, "_repeatfold_kernel", None) is None:
        sc._repeatfold_kernel = _made(spark, "repeatfold.Kernel")
    return sc._repeatfold_kernel


def call(spark: SparkSession, value: Column, options: str, fields: str) -> Column:
    """``array<struct<fields>>``: the kernel's rows for a unit."""
    from pyspark.sql.classic.column import Column as Classic
    from pyspark.sql.classic.column import _to_java_column, _to_seq

    sc = spark.sparkContext
    load = sc._jvm.java.lang.Thread.currentThread().getContextClassLoader().loadClass
    # by reflection: py4j would take the overload for Scala functions, which has no types
    kinds = _array(sc, sc._jvm.java.lang.Class, [load("org.apache.spark.sql.api.java.UDF2"), load("org.apache.spark.sql.types.DataType")])
    kind = spark._jsparkSession.parseDataType(ArrayType(_parse_datatype_string(fields)).json())
    udf = load("org.apache.spark.sql.functions").getMethod("udf", kinds).invoke(None, _array(sc, sc._jvm.java.lang.Object, [_kernel(spark), kind]))
    return Classic(udf.apply(_to_seq(sc, [value, F.lit(options)], _to_java_column)))


def fits(df: DataFrame, col: str, ended: bool = False) -> bool:
    """Texts, arrays of integers and, if ``ended``, arrays of texts go to the JVM; other symbols are coded by the Python path."""
    kind = df.schema[col].dataType
    if ended:
        return isinstance(kind, ArrayType) and isinstance(kind.elementType, StringType)
    return isinstance(kind, StringType) or (isinstance(kind, ArrayType) and isinstance(kind.elementType, IntegerType))


def _options(what: str, engine: str, options: dict) -> str:
    return "|".join([what, engine, *(f"{k}={str(v).lower() if isinstance(v, bool) else v}" for k, v in options.items() if v is not None)])


def rows(df: DataFrame, id_cols: Sequence[str], col: str, fields: str, what: str, engine: str, null_row: bool = False, **options) -> DataFrame:
    """The ids of each unit beside the kernel's rows for it; with ``null_row`` a null unit gives one row of nulls, else none."""
    width = len(_parse_datatype_string(fields).fields)
    parts = _options(what, engine, options | {"nulls": width if null_row else 0})
    return df.select(*(F.col(c) for c in id_cols), F.inline(call(df.sparkSession, F.col(col), parts, fields)))


def histograms(df: DataFrame, keys: Sequence[str], col: str, methods: dict[str, tuple[str, dict]], limit: int = 0) -> DataFrame:
    """``keys, method, stream, x, k``: symbols of the streams of the methods' outputs, counted over the units of a partition.

    ``methods`` has the engine and options of each. A task hands its counts on when they hold ``limit`` symbols (by default a million), so they
    may come more than once.
    """
    spark = df.sparkSession
    units = df.select(*(F.col(c) for c in keys), F.col(col))
    schema = StructType([units.schema[c] for c in keys] + _parse_datatype_string("method string, stream string, x bigint, k bigint").fields)
    lines = "\n".join(f"{name} {_options('streams', engine, options)}" for name, (engine, options) in methods.items())
    encoder = spark._jvm.org.apache.spark.sql.Encoders.row(spark._jsparkSession.parseDataType(schema.json()))
    return DataFrame(units._jdf.mapPartitions(_made(spark, "repeatfold.Kernel$Histograms", lines, len(keys), limit), encoder), spark)
