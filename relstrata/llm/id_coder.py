"""``mixing_coder`` for Spark's own rows: the same bytes from one Java class, compiled on the driver.

Spark brings Janino, which compiles its generated code; it compiles ``IdCoder.java`` too. The jar goes to the
executors as any session's jar does, so they need no compiler and no installation.
"""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

SOURCE = Path(__file__).with_name("IdCoder.java")
#: SQL functions by what the class is told.
NAMES = {False: "relstrata_ids_encode", True: "relstrata_ids_decode"}


def available(spark: SparkSession) -> bool:
    """Whether the session has a JVM of its own; without one ``mixing_coder`` codes in Python workers."""
    try:
        return spark.sparkContext._jvm is not None
    except Exception:  # a remote session raises an error of its own kind
        return False


def _jar(jvm) -> str:
    compiler = jvm.org.codehaus.janino.SimpleCompiler()
    compiler.cook(SOURCE.read_text())
    path = f"{tempfile.mkdtemp(prefix='relstrata-')}/id-coder.jar"
    with zipfile.ZipFile(path, "w") as jar:
        for name, code in compiler.getBytecodes().items():
            jar.writestr(name.replace(".", "/") + ".class", bytes(code))
    return path


def register(spark: SparkSession) -> None:
    """The two SQL functions, once a session."""
    jvm, session = spark.sparkContext._jvm, spark._jsparkSession
    if all(spark.catalog.functionExists(n) for n in NAMES.values()):
        return
    loader = session.sharedState().jarClassLoader()
    try:
        kind = loader.loadClass("relstrata.IdCoder")
    except Exception:  # another session of this JVM may have brought it
        spark.sql(f"ADD JAR '{_jar(jvm)}'")
        kind = loader.loadClass("relstrata.IdCoder")
    for decodes, name in NAMES.items():
        given = spark.sparkContext._gateway.new_array(jvm.Object, 1)
        given[0] = decodes
        session.udf().register(name, kind.getConstructors()[0].newInstance(given), jvm.org.apache.spark.sql.types.DataTypes.BinaryType)


def encoded(spark: SparkSession, ids: str) -> Column:
    """Blocks of ids (little-endian, 32 bits each) as coded bytes."""
    register(spark)
    return F.call_function(NAMES[False], F.col(ids))


def decoded(spark: SparkSession, payload: str) -> Column:
    """Coded bytes as ids; a wrong head or checksum fails the task."""
    register(spark)
    return F.call_function(NAMES[True], F.col(payload))
