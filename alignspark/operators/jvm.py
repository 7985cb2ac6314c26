"""Work on whole arrays that runs in Spark's JVMs.

The driver compiles EditSums.java with Janino, which comes with Spark, and hands the classes to Spark as a jar.
"""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

#: SQL function: a, na, b, nb -> sum of edit distances.
EDIT_SUMS = "alignspark_edit_sums"
_loaders: dict[str, object] = {}


def register(spark: SparkSession) -> None:
    """Make EDIT_SUMS known to this session; classes are made once a Spark application."""
    context = spark.sparkContext
    if context.applicationId not in _loaders:
        compiler = spark._jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(spark._jvm.org.apache.spark.util.Utils.getContextOrSparkClassLoader())
        compiler.cook(Path(__file__).with_name("EditSums.java").read_text())
        path = os.path.join(tempfile.mkdtemp(prefix="alignspark-code-"), "alignspark_edit_sums.jar")
        with zipfile.ZipFile(path, "w") as z:
            for name, code in compiler.getBytecodes().items():
                z.writestr(name.replace(".", "/") + ".class", bytes(code))
        context._jsc.addJar(path)
        _loaders.clear()
        _loaders[context.applicationId] = compiler.getClassLoader()
    made = _loaders[context.applicationId].loadClass("alignspark.EditSums").newInstance()
    spark._jsparkSession.udf().register(EDIT_SUMS, made, spark._jvm.org.apache.spark.sql.types.DataType.fromDDL("bigint"))
