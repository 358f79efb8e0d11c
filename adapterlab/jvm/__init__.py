"""The inner loops of packing, merging and simulating as functions of Spark's own JVM (Kernels.java).

Spark compiles the source with the compiler it uses for its generated code, and executors get the classes as they get any
jar, so nothing else has to be installed. The Python of packing.py, schedule.py and pipeline.py says the same a step at a
time; tests compare the two.
"""

from __future__ import annotations

import os
import tempfile
import threading
import zipfile
from pathlib import Path

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

SOURCE = Path(__file__).with_name("Kernels.java")
PACKED = "bin int, adapter_id string, sample_id bigint, tok_len bigint, solver_path string, stage1 string, stage2 string, nodes bigint"
SLOTS = "slot bigint, group_id int, gb bigint, bin int, adapter_id string, batch bigint, sample_id bigint, tok_len bigint, is_noop boolean, merged bigint"
KERNELS = {"Pack": f"array<struct<{PACKED}>>", "Merge": f"array<struct<{SLOTS}>>", "Simulate": "struct<makespan double, busy double, bubble double>"}


LOCK = threading.Lock()  # plans may be made side by side
_jars: dict[str, str] = {}  # by application
_sessions: set[str] = set()  # where the functions are known


def compiled(spark: SparkSession) -> str:
    """A jar with the classes of the source."""
    compiler = spark._jvm.org.codehaus.janino.SimpleCompiler()
    compiler.cook(SOURCE.read_text())
    path = os.path.join(os.path.realpath(tempfile.mkdtemp(prefix="adapterlab-kernels-")), "adapterlab-kernels.jar")
    classes = compiler.getBytecodes()
    with zipfile.ZipFile(path, "w") as z:
        for name in classes:
            z.writestr(f"{name.replace('.', '/')}.class", bytes(classes[name]))
    return path


def register(spark: SparkSession, application: str) -> None:
    if application not in _jars:
        _jars[application] = compiled(spark)
    spark.sql(f"ADD JAR '{_jars[application]}'")
    inner, array = spark._jsparkSession, spark.sparkContext._gateway.new_array
    loader = inner.sharedState().jarClassLoader()
    for name, kind in KERNELS.items():
        made = loader.loadClass(f"adapterlab.{name}").getDeclaredConstructor(array(spark._jvm.java.lang.Class, 0)).newInstance(array(spark._jvm.java.lang.Object, 0))
        schema = StructType.fromDDL(f"x {kind}")["x"].dataType
        inner.udf().register(f"adapterlab_{name}", made, inner.parseDataType(schema.json()))


def kernel(spark: SparkSession, name: str, *args: Column) -> Column:
    """A call of one of the KERNELS."""
    application = spark.sparkContext.applicationId
    session = f"{application}/{spark._jsparkSession.sessionUUID()}"
    with LOCK:
        if session not in _sessions:
            register(spark, application)
            _sessions.add(session)
    return F.call_udf(f"adapterlab_{name}", *args)


def whole(value: int) -> Column:
    return F.lit(value).cast("bigint")
