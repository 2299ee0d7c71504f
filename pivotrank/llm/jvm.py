"""Functions in Java for loops over single values that neither SQL functions nor arrays can run fast.

A source file of the folder ``java`` is compiled by the compiler that Spark itself carries for its generated
code, packed into a jar and added to the session, which hands it to every executor, later ones too.
"""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_SOURCES = Path(__file__).parent / "java"


def register(spark: SparkSession, name: str, functions: dict[str, tuple[str, str]]) -> None:
    """SQL functions of the session: name of each to (class within ``name``.java, type). Once a session."""
    if all(spark.catalog.functionExists(f) for f in functions):
        return
    jvm = spark._jvm
    compiler = jvm.org.codehaus.janino.SimpleCompiler()
    compiler.cook((_SOURCES / f"{name}.java").read_text(encoding="utf-8"))
    path = os.path.join(tempfile.mkdtemp(prefix="jar-"), f"{name}.jar")  # the driver serves it to the executors
    with zipfile.ZipFile(path, "w") as jar:
        for entry in compiler.getBytecodes().entrySet():
            jar.writestr(entry.getKey().replace(".", "/") + ".class", bytes(entry.getValue()))
    spark.sql(f"ADD JAR '{path}'")
    for f, (inner, kind) in functions.items():
        own = compiler.getClassLoader().loadClass(f"pivotrank.{name}${inner}").getDeclaredConstructors()[0].newInstance(None)
        made = _function(spark, own, jvm.org.apache.spark.sql.types.DataType.fromDDL(kind))
        spark._jsparkSession.udf().register(f, made.asNondeterministic())  # else a plan may hold, and run, several copies of a call


def _function(spark: SparkSession, own, kind):
    """functions.udf of the interface that ``own`` implements, called by reflection: by name alone another one would be taken."""
    jvm, array = spark._jvm, spark.sparkContext._gateway.new_array
    of, given = array(jvm.java.lang.Class, 2), array(jvm.java.lang.Object, 2)
    of[0], of[1] = own.getClass().getInterfaces()[0], jvm.java.lang.Class.forName("org.apache.spark.sql.types.DataType")
    given[0], given[1] = own, kind
    return jvm.java.lang.Class.forName("org.apache.spark.sql.functions").getMethod("udf", of).invoke(None, given)
