"""token_coder's coder in Spark's own JVMs, where it takes an id at a time: the same bytes for less work.

The driver compiles TokenCoder.java with Janino, which comes with Spark, and hands the classes to Spark as a jar.
"""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

from .token_coder import SQUASH, STRETCH

#: SQL functions: ids -> file bytes; data, lengths, doc_ids, no_id of a segment -> its documents.
PACK, DOCS = "alignspark_token_pack", "alignspark_token_docs"
DOC = "array<struct<doc_id: bigint, at: bigint, n_tokens: bigint, ids_crc32: bigint>>"
_loaders: dict[str, object] = {}


def _loader(spark: SparkSession):
    """Class loader of the compiled classes, which are made once a Spark application."""
    context = spark.sparkContext
    if context.applicationId not in _loaders:
        source = Path(__file__).with_name("TokenCoder.java").read_text()
        for name, values in (("@STRETCH@", STRETCH + 2048), ("@SQUASH@", SQUASH)):
            source = source.replace(name, "".join(f"{v:03x}" for v in values.tolist()))
        compiler = spark._jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(spark._jvm.org.apache.spark.util.Utils.getContextOrSparkClassLoader())
        compiler.cook(source)
        path = os.path.join(tempfile.mkdtemp(prefix="alignspark-code-"), "alignspark_token_coder.jar")
        with zipfile.ZipFile(path, "w") as z:
            for name, code in compiler.getBytecodes().items():
                z.writestr(name.replace(".", "/") + ".class", bytes(code))
        context._jsc.addJar(path)
        _loaders.clear()
        _loaders[context.applicationId] = compiler.getClassLoader()
    return _loaders[context.applicationId]


def register(spark: SparkSession) -> None:
    """Make PACK and DOCS known to this session."""
    for name, made, kind in ((PACK, "Pack", "binary"), (DOCS, "Docs", DOC)):
        run = _loader(spark).loadClass(f"alignspark.TokenCoder${made}").newInstance()
        spark._jsparkSession.udf().register(name, run, spark._jvm.org.apache.spark.sql.types.DataType.fromDDL(kind))
