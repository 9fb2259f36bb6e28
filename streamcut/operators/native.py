"""``Streams.java`` as functions of Spark SQL: compiled by the compiler that Spark has for generated code, sent as a jar."""

from __future__ import annotations

import tempfile
import threading
import uuid
import zipfile
from importlib.resources import files

from pyspark.sql import SparkSession

#: Parts that a replica mask of ``Streams.java`` holds.
PARTS = 128
STREAMS, KEY, GRID = "streamcut_streams", "streamcut_key", "streamcut_grid"
#: Of a text in lower case: array<long>, and array<struct<a long, b long>>.
WORDS, PAIRS = "streamcut_words", "streamcut_pairs"
_lock, _known = threading.Lock(), {}


def register(spark: SparkSession) -> None:
    """Makes the functions known to the session and its executors, once."""
    with _lock:
        if _known.get("session") is spark:
            return
        compiler = spark._jvm.org.codehaus.janino.SimpleCompiler()
        compiler.setParentClassLoader(spark._jvm.java.lang.Thread.currentThread().getContextClassLoader())
        compiler.cook(files(__package__).joinpath("Streams.java").read_text())
        path = f"{tempfile.mkdtemp(prefix='streamcut-')}/streams-{uuid.uuid4().hex[:12]}.jar"
        with zipfile.ZipFile(path, "w") as jar:
            for name, code in dict(compiler.getBytecodes()).items():
                jar.writestr(name.replace(".", "/") + ".class", bytes(code))
        spark.sql(f"ADD JAR '{path}'")
        types = spark._jvm.org.apache.spark.sql.types.DataTypes
        words, pairs = types.createArrayType(types.LongType, False), spark._jvm.org.apache.spark.sql.types.DataType.fromDDL("array<struct<a: bigint, b: bigint>>")
        for name, kind, returns in ((STREAMS, "Streams", types.StringType), (KEY, "Streams$Key", types.BinaryType), (GRID, "Streams$Grid", types.LongType), (WORDS, "Streams$Words", words), (PAIRS, "Streams$Pairs", pairs)):
            call = compiler.getClassLoader().loadClass(f"streamcut.{kind}").getDeclaredConstructor(None).newInstance(None)
            spark._jsparkSession.udf().register(name, call, returns)
        _known["session"] = spark
