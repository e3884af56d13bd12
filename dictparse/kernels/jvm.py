"""The parses of `kernels.quick` and the decoder as functions of Spark's own processes, without a Python stage.

The source beside this file is compiled by the compiler that Spark brings for its generated code; executors get the classes as a jar from
the driver. `kernels.quick` stays the reference; tests compare the two.
"""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_SHAPES = {"Back": "string", "Written": "string", "Summary": "struct<n long, sigma long, z long, combine_n long, cut_n long, repeat_n long, trie_nodes long, split_nodes long, kernel_ms double>"}
_loaders: dict[str, object] = {}


def _compiled(spark: SparkSession):
    """The class loader of the compiled source; once for an application, which then has the jar."""
    sc = spark.sparkContext
    if sc.applicationId not in _loaders:
        with open(os.path.join(os.path.dirname(os.path.abspath(__file__)), "JvmParse.java")) as f:
            source = f.read()
        compiler = sc._jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(sc._jvm.org.apache.spark.util.Utils.getContextOrSparkClassLoader())
        compiler.cook(source)
        path = os.path.join(tempfile.mkdtemp(prefix="dictparse-"), "dictparse-jvm.jar")
        with zipfile.ZipFile(path, "w") as jar:
            for name, code in dict(compiler.getBytecodes()).items():
                jar.writestr(name.replace(".", "/") + ".class", bytes(code))
        sc._jsc.addJar(path)
        _loaders.clear()
        _loaders[sc.applicationId] = compiler.getClassLoader()
    return _loaders[sc.applicationId]


def function(spark: SparkSession, what: str, text: Column, scheme: str | Column, lookahead: str | Column = "none") -> Column:
    """'Back': the text as its factors give it; 'Summary': counts; 'Written': all numbers of the parse."""
    name = f"dictparse_{what.lower()}"
    made = _compiled(spark).loadClass(f"JvmParse${what}").getDeclaredConstructors()[0].newInstance(spark.sparkContext._gateway.new_array(spark._jvm.java.lang.Object, 0))
    shape = spark._jvm.org.apache.spark.sql.types.DataType.fromDDL(_SHAPES[what])
    spark._jsparkSession.udf().register(name, made, shape)
    return F.call_function(name, text, F.lit(scheme), F.lit(lookahead))  # lit() leaves columns as they are


def mapped(df: DataFrame, what: str, options: list[str], shape: str) -> DataFrame:
    """The rows that a compiled function of a partition's rows, 'Parts' or 'Counts', makes of the frame's; fields by position."""
    spark = df.sparkSession
    values = spark.sparkContext._gateway.new_array(spark._jvm.java.lang.Object, len(options))
    for k, v in enumerate(options):
        values[k] = v
    made = _compiled(spark).loadClass(f"JvmParse${what}").getDeclaredConstructors()[0].newInstance(values)
    encoder = spark._jvm.org.apache.spark.sql.Encoders.row(spark._jvm.org.apache.spark.sql.types.StructType.fromDDL(shape))
    return DataFrame(df._jdf.mapPartitions(made, encoder), spark)


def summary_columns() -> str:
    return _SHAPES["Summary"].removeprefix("struct<").removesuffix(">")
